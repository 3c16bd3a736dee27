"""Substring dedup over words, by recompression.

Rounds rename a document's words: first each run of one word, then, in each round, each pair of neighbours of which the
first is on the left and the second on the right side of a partition of all names, drawn anew in each round.  A name is a hash
of what it stands for, so all tasks give equal strings equal names without asking each other, and two
equal windows hold equal names inside, except near their ends.  For every name the words are tracked that decide it; a name
whose deciding words fit in a window is an anchor of all windows around them.

1. Anchors are counted over the corpus; those that occur once rule out every window that holds them.  Windows
   without any anchor are counted directly.
2. What is left is verified: a window counts as repeated if the code of its words occurs anywhere else: the bucket bits of one
   64-bit hash and all of another.

Null texts have no words; texts shorter than a window lose nothing; whole copies are counted once.  Repeated rows are copies.
Null ids are kept.  Extra columns stay in ``remove_repeats``.  An empty table gives an empty result.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import repeats, storage
from .textkit import BASE_A, BASE_B, U64, encoded, lean, mix, runs_to_spans, slices, unpack_all, window_hash, word_codes, words_of

WINDOW, ROUNDS = 35, 5
BLANKS = frozenset(b" \t\n\x0b\x0c\r")
FAR = 1 << 40
#: Words that are named at once, and bytes that are split at once; a longer text is taken in overlapping stretches.
STRETCH, SPLIT = 100_000, 1 << 20
WINDOW_MARK = U64(0x5BD1E995A7C3F00D)


class Names:
    """Names of consecutive words after the rounds, for the words of several documents, one after the other."""

    def __init__(self, codes: np.ndarray, doc: np.ndarray, rounds: int = ROUNDS):
        n = len(codes)
        begin = np.r_[True, codes[1:] != codes[:-1]] if n else np.zeros(0, dtype=bool)
        begin[1:] |= doc[1:] != doc[:-1]
        first = np.flatnonzero(begin)
        last = np.r_[first[1:], n]
        self.name = np.where(last - first > 1, mix(codes[first] ^ mix((last - first).astype(U64))), codes[first])
        self.doc = doc[first]
        # A run ends where another word comes; so its neighbours decide it too, and the text's ends cannot be seen from inside.
        self.low = np.where(np.r_[True, self.doc[1:] != self.doc[:-1]], -FAR, first - 1)
        self.high = np.where(np.r_[self.doc[1:] != self.doc[:-1], True], FAR, last + 1) if n else last
        for r in range(rounds):
            self._pairs(U64((r + 1) * 0x9E3779B97F4A7C15 & (1 << 64) - 1))

    def _pairs(self, salt: np.uint64) -> None:
        n = len(self.name)
        if n < 2:
            return
        right = (mix(self.name ^ salt) & U64(1)).astype(bool)
        joined = self.doc[1:] == self.doc[:-1]
        opens = np.r_[~right[:-1] & right[1:] & joined, False]
        closes = np.r_[False, opens[:-1]]
        after, before = np.r_[joined, False], np.r_[False, joined]
        low_next, low_prev = np.r_[self.low[1:], 0], np.r_[0, self.low[:-1]]
        high_next, high_prev = np.r_[self.high[1:], 0], np.r_[0, self.high[:-1]]
        # A name of the left side needs the next one, paired or not; one of the right side needs the one before.
        low = np.where(right, np.where(before, np.minimum(self.low, low_prev), -FAR), np.where(after, np.minimum(self.low, low_next), self.low))
        high = np.where(right, np.where(before, np.maximum(self.high, high_prev), self.high), np.where(after, np.maximum(self.high, high_next), FAR))
        pair = mix(self.name[:-1] * U64(0xC2B2AE3D27D4EB4F) ^ mix(self.name[1:] + U64(0x165667B19E3779F9)))
        name = np.where(opens, np.r_[pair, U64(0)], self.name)
        stay = ~closes
        self.name, self.doc, self.low, self.high = name[stay], self.doc[stay], low[stay], high[stay]


def codes_of(text: str | None) -> np.ndarray:
    """Codes of all words; a long text is split piece by piece, so that its words are never all strings at once."""
    raw = encoded(text)
    if len(raw) <= SPLIT:
        return word_codes(raw.split())
    out, at = [], 0
    while at < len(raw):
        end = min(at + SPLIT, len(raw))
        while end < len(raw) and raw[end] not in BLANKS:  # never inside a word
            end += 1
        out.append(word_codes(raw[at:end].split()))
        at = end
    return np.concatenate(out)


def coded(texts: list, overlap: int):
    """Runs of whole short texts, and overlapping stretches of long ones: (number of the first text, begins, codes, start).

    ``begins`` has where each text's words begin, and the end.  Words from ``STRETCH`` on belong to the next stretch.
    """
    first, held, size = 0, [], 0

    def run():
        return first, np.r_[0, np.cumsum([len(c) for c in held])].astype(np.int64), np.concatenate(held), 0

    for d, text in enumerate(texts):
        codes = codes_of(text)
        if held and size + len(codes) > STRETCH:
            yield run()
            first, held, size = d, [], 0
        if len(codes) <= STRETCH:
            held.append(codes)
            size += len(codes)
            continue
        for at in range(0, len(codes), STRETCH):
            part = codes[at : at + STRETCH + overlap]
            yield d, np.array([0, len(part)]), part, at
        first = d + 1
    if held:
        yield run()


def windows(codes: np.ndarray, begins: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Both hashes of all runs of ``length`` words, and whether the run lies inside one document."""
    a, b = window_hash(codes[:, 0], length, BASE_A), window_hash(codes[:, 1], length, BASE_B)
    inside = np.zeros(len(a), dtype=bool)
    for x, y in zip(begins, begins[1:], strict=False):
        if y - x >= length:
            inside[x : y - length + 1] = True
    return a, b, inside


def anchors_over(names: Names, some: np.ndarray, n: int, length: int) -> np.ndarray:
    """How many of the chosen names decide themselves inside each window of ``length`` words."""
    change = np.zeros(n + 2, dtype=np.int64)
    np.add.at(change, np.maximum(names.high[some] - length, 0), 1)
    np.add.at(change, names.low[some] + 1, -1)
    return np.cumsum(change)[:n]


def _owned(at: np.ndarray, begins: np.ndarray) -> np.ndarray:
    """Of window starts, those that the next stretch does not have too."""
    return at[at - begins[np.searchsorted(begins, at, side="right") - 1] < STRETCH]


def anchor_emitter(length: int):
    """Places 2 * number of an anchor among a text's names, and 2 * start + 1 of a window without anchors.

    Names of a stretch are numbered from its start on, with room for the overlap.  A window's anchors are decided by its own words, so
    it has the same ones in any stretch; anchors in an overlap are met twice, which rules out less and loses nothing.
    """

    def emit(texts):
        for first, begins, codes, start in coded(texts, length - 1):
            doc = np.repeat(np.arange(len(begins) - 1), np.diff(begins))
            names = Names(codes[:, 0], doc)
            fit = names.high - names.low <= length
            a, b, inside = windows(codes, begins, length)
            bare = _owned(np.flatnonzero(inside & (anchors_over(names, fit, len(codes), length)[: len(a)] == 0)), begins)
            number = np.arange(len(names.doc)) - np.searchsorted(names.doc, names.doc) + start // STRETCH * (STRETCH + length)
            at = np.flatnonzero(fit & (np.diff(begins)[names.doc] >= length))
            yield (
                first + np.concatenate([names.doc[at], doc[bare]]), np.concatenate([2 * number[at], 2 * (bare - begins[doc[bare]] + start) + 1]),
                np.concatenate([mix(names.name[at]), a[bare] ^ WINDOW_MARK]), np.concatenate([mix(names.name[at] ^ WINDOW_MARK), b[bare]]),
            )

    return emit


def window_emitter(length: int):
    """Starts of the windows that the anchors do not rule out."""

    def emit(places, texts):
        for first, begins, codes, start in coded(texts, length - 1):
            doc = np.repeat(np.arange(len(begins) - 1), np.diff(begins))
            names = Names(codes[:, 0], doc)
            fit = names.high - names.low <= length
            again, bare = np.zeros(len(names.doc) + 1, dtype=bool), np.zeros(len(codes) + 1, dtype=bool)
            for d in range(len(begins) - 1):
                p = unpack_all(places[first + d])
                number = p[p % 2 == 0] // 2 - start // STRETCH * (STRETCH + length)
                low, high = np.searchsorted(names.doc, [d, d + 1])
                again[low + number[(number >= 0) & (number < high - low)]] = True
                at = p[p % 2 == 1] // 2 - start
                bare[begins[d] + at[(at >= 0) & (at < begins[d + 1] - begins[d])]] = True
            a, b, inside = windows(codes, begins, length)
            total, known = (anchors_over(names, x, len(codes), length)[: len(a)] for x in (fit, fit & again[:-1]))
            at = _owned(np.flatnonzero(inside & np.where(total > 0, total == known, bare[: len(a)])), begins)
            yield first + doc[at], at - begins[doc[at]] + start, a[at], b[at]

    return emit


def repeated_windows(docs: DataFrame, length: int = WINDOW) -> tuple[DataFrame, DataFrame]:
    """The marked documents (see ``repeats.with_copies_marked``), and doc_id, mark, places: the starts of repeated windows."""
    spark = docs.sparkSession
    marked = repeats.with_copies_marked(docs)
    own = marked.where(~F.col("spare"))
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    anchors = storage.spill(repeats.repeated_places(own, anchor_emitter(length), key_bytes=5, most_entries=size // 12), "anchors")
    repeats.forget_shuffles(spark)
    found = storage.spill(repeats.repeated_places(repeats.with_places(own, anchors, "inner"), window_emitter(length), ("places", "text"), most_entries=size // 2), "windows")
    storage.release(anchors)
    repeats.forget_shuffles(spark)
    return marked, found


def kept_words(words: list[bytes], starts: np.ndarray, copied: bool, length: int) -> list[bytes]:
    if copied and len(words) >= length:
        return []
    spans = runs_to_spans(starts, length)
    if not len(spans):
        return words
    out, at = [], 0
    for a, b in spans:
        out += words[at:a]
        at = b
    return out + words[at:]


def remove_repeats(docs: DataFrame, length: int = WINDOW) -> DataFrame:
    """``docs`` without the words of repeated windows: text is the kept words joined by one blank where any went, else unchanged; n_chars follows."""
    rest = [c for c in docs.columns if c not in ("doc_id", "text")]
    marked, found = repeated_windows(docs, length)
    copied = marked.where("copied").select("doc_id", "mark").distinct().withColumn("copied", F.lit(True))
    whole = storage.small(storage.spill(copied, "copied")).withColumnRenamed("doc_id", "_of").withColumnRenamed("mark", "_mark")
    # Other columns travel in one struct, so their names cannot clash with those used here.
    held = F.struct(*rest) if rest else F.struct(F.lit(0).alias("none"))
    keyed = docs.select("doc_id", "text", held.alias("rest"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("mark"))
    joined = repeats.with_places(keyed, storage.small(found), "left")
    joined = joined.join(whole, joined["doc_id"].eqNullSafe(whole["_of"]) & (joined["mark"] == whole["_mark"]), "left").select("doc_id", "rest", "text", "places", "copied")

    @lean
    def run(batches):
        for ids, others, places_in, all_in, texts_in in slices(batches, ["doc_id", "rest", "places", "copied", "text"], as_lists=("places", "copied", "text")):
            texts = []
            for text, places, all_ in zip(texts_in, places_in, all_in, strict=True):
                if places is None and not all_:
                    texts.append(text)
                    continue
                words = words_of(text)
                kept = kept_words(words, unpack_all(places), bool(all_), length)
                texts.append(text if len(kept) == len(words) else b" ".join(kept).decode("utf-8", "surrogatepass"))
            yield pa.RecordBatch.from_arrays([ids, others, pa.array(texts, pa.string())], ["doc_id", "rest", "text"])

    out = joined.mapInArrow(run, joined.select("doc_id", "rest", "text").schema)
    chars = F.length("text").cast("long")
    return out.select(*[F.col(c) if c in ("doc_id", "text") else chars.alias(c) if c == "n_chars" else F.col("rest")[c].alias(c) for c in docs.columns])


DIGESTS = "doc_id long, n_words long, n_removed long, kept_sha256 string"


def op5_substrings(spark, sf_dir: str) -> DataFrame:
    marked, found = repeated_windows(storage.table(spark, sf_dir, "documents"))
    joined = repeats.with_places(marked, storage.small(found), "left")

    @lean
    def run(batches):
        for ids, copied, places, texts in slices(batches, ["doc_id", "copied", "places", "text"]):
            rows = []
            for text, starts, all_ in zip(texts, places, copied, strict=True):
                words = words_of(text)
                kept = kept_words(words, unpack_all(starts), all_, WINDOW)
                rows.append((len(words), len(words) - len(kept), hashlib.sha256(b" ".join(kept)).hexdigest()))
            cols = list(zip(*rows, strict=True))
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2])], [x.split()[0] for x in DIGESTS.split(", ")])

    return joined.select("doc_id", "copied", "places", "text").mapInArrow(run, DIGESTS)


ORACLE = r"""
WITH d AS (SELECT row_number() OVER () AS k, doc_id, list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
s AS (SELECT k, generate_subscripts(w, 1) AS i, w FROM d WHERE len(w) >= 35),
h AS (SELECT k, i, md5_number(array_to_string(w[i:i + 34], ' ')) AS h FROM s WHERE i <= len(w) - 34),
r AS (SELECT k, i FROM (SELECT k, i, count(*) OVER (PARTITION BY h) AS n FROM h) WHERE n > 1),
c AS (SELECT DISTINCT k, i + j AS i FROM r, range(35) t(j)),
g AS (SELECT k, list(i) AS gone FROM c GROUP BY k),
f AS (SELECT doc_id, w, gone, CASE WHEN gone IS NULL THEN w ELSE [w[i] FOR i IN range(1, len(w) + 1) IF NOT list_contains(gone, i)] END AS kept FROM d LEFT JOIN g USING (k))
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(len(w) - len(kept) AS BIGINT) AS n_removed, sha256(array_to_string(kept, ' ')) AS kept_sha256 FROM f
"""
