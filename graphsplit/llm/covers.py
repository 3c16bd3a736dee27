"""Substring dedup over bytes: suffixes of a difference cover's places first, then one bucket of suffixes at a time.

The cover's places (a twelfth of a text's places, chosen by their residue) have the property that for any two places there
is one shift below the period that brings both into the cover.  So if the strings of ``LENGTH`` bytes at two places are
equal, then so are the ``LENGTH - period + 1`` bytes at two cover places inside them.

1. Cover suffixes are ranked: those equal in these bytes get one name, and names met once rule out every string
   around that shift.
2. The remaining suffixes are dealt to buckets of hash range, and each bucket is sorted by itself; ties of equal hashes
   are told apart by a second one.  A task holds one bucket; the corpus's suffixes are never together.

A suffix's rank is a pair of 64-bit hashes, so no comparison reads the texts again.  Null texts are empty;
matches never cross rows; texts shorter than the length lose nothing; whole copies are counted once.  Repeated rows are copies,
null ids are kept.  An empty table gives an empty result.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import repeats, storage
from .textkit import BASE_A, BASE_B, U64, encoded, lean, mix, powers, runs_to_spans, slices, unpack_all

LENGTH = 200
#: A perfect difference set; each residue but 0 is one difference of two of them.
PERIOD, COVER = 133, (0, 1, 3, 12, 20, 34, 38, 81, 88, 94, 104, 109)


#: Bytes of texts that are hashed at once; a longer text is taken in overlapping stretches.
STRETCH = 1 << 19


class Bytes:
    """A stretch of bytes with hashes of any substrings of one length."""

    def __init__(self, data: bytes):
        self.data = np.frombuffer(data, dtype=np.uint8)

    def hashes(self, at: np.ndarray, length: int, base: int) -> np.ndarray:
        """Hashes of the ``length`` bytes from each of ``at`` on."""
        n = len(self.data)
        code = mix(np.arange(256, dtype=U64) * U64(base) + U64(length))
        total = np.empty(n + 1, dtype=U64)
        total[0] = 0
        codes = code[self.data]
        codes *= powers(base, n)
        np.cumsum(codes, out=total[1:])
        out = total[at + length]
        out -= total[at]
        out *= powers(pow(base, -1, 1 << 64), n)[at]
        return mix(out)


def stretches(texts: list, overlap: int):
    """Runs of whole short texts, and overlapping stretches of long ones: (number of the first text, begins, bytes, start inside the text).

    ``begins`` has where each text begins, and the end.  Places from ``STRETCH`` on belong to the next stretch.
    """
    first, held, size = 0, [], 0

    def run():
        return first, np.r_[0, np.cumsum([len(b) for b in held])].astype(np.int64), b"".join(held), 0

    for d, text in enumerate(texts):
        raw = encoded(text)
        if held and size + len(raw) > STRETCH:
            yield run()
            first, held, size = d, [], 0
        if len(raw) <= STRETCH:
            held.append(raw)
            size += len(raw)
            continue
        for at in range(0, len(raw), STRETCH):
            part = raw[at : at + STRETCH + overlap]
            yield d, np.array([0, len(part)]), part, at
        first = d + 1
    if held:
        yield run()


def cover_emitter(length: int, period: int, cover: tuple[int, ...]):
    """Cover places, hashed over the bytes that equal strings of ``length`` share from a common cover place on."""
    own = length - period + 1
    chosen = np.zeros(period, dtype=bool)
    chosen[list(cover)] = True

    def emit(texts):
        sizes = np.array([len(encoded(t)) for t in texts], dtype=np.int64)
        for first, begins, data, start in stretches(texts, own - 1):
            doc = np.repeat(np.arange(len(begins) - 1, dtype=np.int32), np.diff(begins))
            place = np.arange(len(data)) - begins[doc] + start
            at = np.flatnonzero(chosen[place % period] & (place < start + STRETCH))
            at = at[(place[at] + own <= sizes[first + doc[at]]) & (sizes[first + doc[at]] >= length)]
            b = Bytes(data)
            yield first + doc[at], place[at], b.hashes(at, own, BASE_A), b.hashes(at, own, BASE_B)

    return emit


def suffix_emitter(length: int, period: int):
    """Starts of strings with a repeated cover place at some shift below the period."""

    def emit(places, texts):
        for first, begins, data, start in stretches(texts, length - 1):
            change = np.zeros(len(data) + 1, dtype=np.int32)
            for d in range(len(begins) - 1):
                at = begins[d] + unpack_all(places[first + d]) - start
                low = np.maximum(at - period + 1, begins[d])
                near = (at >= begins[d]) & (low < begins[d + 1])
                np.add.at(change, low[near], 1)
                np.add.at(change, np.minimum(at[near] + 1, begins[d + 1]), -1)
            at = np.flatnonzero(np.cumsum(change)[:-1] > 0)
            doc = np.searchsorted(begins, at, side="right") - 1
            fits = (at + length <= begins[doc + 1]) & (at - begins[doc] < STRETCH)
            at, doc = at[fits], doc[fits]
            b = Bytes(data)
            yield first + doc, at - begins[doc] + start, b.hashes(at, length, BASE_A), b.hashes(at, length, BASE_B)

    return emit


def repeated_strings(docs: DataFrame, length: int = LENGTH, period: int = PERIOD, cover: tuple[int, ...] = COVER) -> tuple[DataFrame, DataFrame]:
    """The marked documents (see ``repeats.with_copies_marked``), and doc_id, mark, places: starts of repeated strings."""
    spark = docs.sparkSession
    marked = repeats.with_copies_marked(docs)
    own = marked.where(~F.col("spare"))
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    ranked = storage.spill(repeats.repeated_places(own, cover_emitter(length, period, cover), key_bytes=5, most_entries=size * len(cover) // period), "cover")
    repeats.forget_shuffles(spark)
    found = storage.spill(repeats.repeated_places(repeats.with_places(own, ranked, "inner"), suffix_emitter(length, period), ("places", "text"), most_entries=size), "suffixes")
    storage.release(ranked)
    repeats.forget_shuffles(spark)
    return marked, found


def removed_spans(size: int, starts: np.ndarray, copied: bool, length: int) -> np.ndarray:
    """Maximal runs of bytes to remove; runs that touch are one."""
    if copied and size >= length:
        return np.array([[0, size]])
    return runs_to_spans(starts, length)


DIGESTS = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"


def op6_suffixes(spark, sf_dir: str) -> DataFrame:
    marked, found = repeated_strings(storage.table(spark, sf_dir, "documents"))
    joined = repeats.with_places(marked, storage.small(found), "left")

    @lean
    def run(batches):
        for ids, copied, places, texts in slices(batches, ["doc_id", "copied", "places", "text"]):
            rows = []
            for text, starts, all_ in zip(texts, places, copied, strict=True):
                raw = encoded(text)
                spans = removed_spans(len(raw), unpack_all(starts), all_, LENGTH)
                digest, at = hashlib.sha256(), 0
                for x, y in spans.tolist():
                    digest.update(raw[at:x])
                    at = y
                digest.update(raw[at:])
                rows.append((len(raw), int((spans[:, 1] - spans[:, 0]).sum()), len(spans), digest.hexdigest()))
            cols = list(zip(*rows, strict=True))
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), *[pa.array(c, pa.int64()) for c in cols[:3]], pa.array(cols[3])], [x.split()[0] for x in DIGESTS.split(", ")])

    return joined.select("doc_id", "copied", "places", "text").mapInArrow(run, DIGESTS)


ORACLE = r"""
WITH d AS (SELECT row_number() OVER () AS k, doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
p AS (SELECT k, i, md5_number(substr(h, 2 * i + 1, 400)) AS m FROM (SELECT k, h, unnest(range(0, length(h) // 2 - 199)) AS i FROM d)),
r AS (SELECT k, i FROM (SELECT k, i, count(*) OVER (PARTITION BY m) AS n FROM p) WHERE n > 1),
g AS (SELECT k, i, sum(fresh) OVER (PARTITION BY k ORDER BY i) AS s FROM (SELECT k, i, CASE WHEN i - lag(i) OVER (PARTITION BY k ORDER BY i) <= 200 THEN 0 ELSE 1 END AS fresh FROM r)),
q AS (SELECT k, a, b, coalesce(lag(b) OVER (PARTITION BY k ORDER BY a), 0) AS last FROM (SELECT k, min(i) AS a, max(i) + 200 AS b FROM g GROUP BY k, s)),
f AS (SELECT k, count(*) AS n_spans, sum(b - a) AS n_removed, string_agg(substr(h, 2 * last + 1, 2 * (a - last)), '' ORDER BY a) || substr(any_value(h), 2 * max(b) + 1) AS kept FROM q JOIN d USING (k) GROUP BY k)
SELECT doc_id, CAST(length(h) // 2 AS BIGINT) AS n_bytes, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, coalesce(n_spans, 0) AS n_spans, sha256(unhex(coalesce(kept, h))) AS kept_sha256 FROM d LEFT JOIN f USING (k)
"""
