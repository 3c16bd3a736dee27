"""Which of many hashed places of a corpus hold what some other place holds too: one exact, skew-proof round.

A map task hashes places of its documents (a place: a number inside a document), keeps what its own batch already shows
to be repeated, and sends every distinct hash once, by bucket of hash range.  A bucket's task sorts its hashes and sends back
to each batch which of its entries were met elsewhere.  So a passage that a third of all documents share costs a batch one
entry, and no task holds more than its bucket or its batch.
"""

from __future__ import annotations

import gc
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import storage
from .textkit import U64, give_back, lean, pack, slices, unpack

#: Entries that a map task gathers before it sends them, and those that one bucket is to get.
BATCH_ENTRIES, BUCKET_ENTRIES = 500_000, 4_000_000
ROWS = pa.schema([("bucket", pa.int32()), ("uid", pa.int64()), ("kind", pa.int8()), ("keys", pa.binary()), ("many", pa.binary()), ("places", pa.binary())])
ROWS_SQL = "bucket int, uid long, kind byte, keys binary, many binary, places binary"
#: Kinds of rows: a batch's documents; where its entries lie; entries known to be repeated; hashes sent to a bucket.
DOCUMENTS, ENTRIES, REPEATED, SENT = 0, 1, 2, 3


def bucket_count(spark, most_entries: int = 0) -> int:
    """A power of two: two or more buckets for each shuffle partition, and as many as ``most_entries`` ask for."""
    wanted = max(2 * storage.width(spark), -(-most_entries // BUCKET_ENTRIES))
    return 1 << (wanted - 1).bit_length()


def _send(uid: int, docs: list, keys: np.ndarray, seconds: np.ndarray, doc: np.ndarray, place: np.ndarray, buckets: int, key_bytes: int) -> list[tuple]:
    order = np.argsort(keys)
    ordered = keys[order]
    first = np.r_[True, ordered[1:] != ordered[:-1]]
    size = np.diff(np.r_[np.flatnonzero(first), len(ordered)])
    many = np.empty(len(keys), dtype=bool)
    many[order] = np.repeat(size > 1, size)
    sent = np.zeros(len(keys), dtype=bool)
    sent[order[first]] = True  # one of each
    at = np.flatnonzero(sent)
    shift = U64(64 - (buckets.bit_length() - 1))
    bucket = (keys[at] >> shift).astype(np.uint16 if buckets <= 1 << 16 else np.uint32)
    by = np.argsort(bucket, kind="stable")
    at, bucket = at[by], bucket[by]
    edges = np.searchsorted(bucket, np.arange(buckets + 1))
    home = ((uid >> 24) * 40503 + (uid & 0xFFFFFF)) % buckets  # spreads the rows that only pass
    rows = [
        (home, uid, DOCUMENTS, b"".join(int(t).to_bytes(8, "little", signed=True) for _, t in docs), None, _ids([d for d, _ in docs])),
        (home, uid, ENTRIES, pack(doc), None, pack(place)),
        (home, uid, REPEATED, None, None, pack(np.flatnonzero(many))),
    ]
    for b in np.flatnonzero(np.diff(edges)):
        own = at[edges[b] : edges[b + 1]]
        rows.append((int(b), uid, SENT, np.ascontiguousarray(seconds[own].view(np.uint8).reshape(-1, 8)[:, :key_bytes]).tobytes(), np.packbits(many[own]).tobytes(), pack(own)))
    return rows


def _ids(ids: list) -> bytes:
    """Integers or nulls as bytes: a flag and 8 bytes each."""
    return b"".join(bytes([i is None]) + int(i or 0).to_bytes(8, "little", signed=True) for i in ids)


def _read_ids(b: bytes) -> list:
    return [None if b[i] else int.from_bytes(b[i + 1 : i + 9], "little", signed=True) for i in range(0, len(b), 9)]


def _record(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), ROWS, strict=True)], schema=ROWS)


def _widened(b: bytes, key_bytes: int) -> np.ndarray:
    out = np.zeros((len(b) // key_bytes, 8), dtype=np.uint8)
    out[:, :key_bytes] = np.frombuffer(b, dtype=np.uint8).reshape(-1, key_bytes)
    return out.view(U64).ravel()


def _meet(table: pa.Table, key_bytes: int) -> pa.Table:
    """One bucket: for each batch, which of the entries it sent are met elsewhere; rows of other kinds pass."""
    kinds = table.column("kind").to_numpy()
    passing = table.filter(pa.array(kinds != SENT))
    sent = table.filter(pa.array(kinds == SENT))
    if not len(sent):
        return passing
    keys = [_widened(k, key_bytes) for k in sent.column("keys").to_pylist()]
    many = np.concatenate([np.unpackbits(np.frombuffer(m, dtype=np.uint8), count=len(k)) for m, k in zip(sent.column("many").to_pylist(), keys, strict=True)]).astype(bool)
    every = np.concatenate(keys)
    order = np.argsort(every)
    ordered = every[order]
    same = ordered[1:] == ordered[:-1]
    met = np.zeros(len(every), dtype=bool)
    met[order[1:][same]] = True
    met[order[:-1][same]] = True
    met &= ~many  # their batch knows already
    rows, start = [], 0
    for k, uid, places in zip(keys, sent.column("uid").to_pylist(), sent.column("places").to_pylist(), strict=True):
        own = met[start : start + len(k)]
        start += len(k)
        if own.any():
            rows.append((0, uid, REPEATED, None, None, pack(unpack(places)[own])))
    return pa.concat_tables([passing, pa.Table.from_batches([_record(rows)])]) if rows else passing


def _gather(table: pa.Table) -> pa.Table:
    """One batch: the repeated places of each of its documents."""
    kinds = table.column("kind").to_pylist()
    rows = table.to_pylist()
    found = [unpack(r["places"]) for r in rows if r["kind"] == REPEATED]
    entries = np.unique(np.concatenate(found)) if found else np.zeros(0, dtype=np.int64)
    out: list[tuple] = []
    if len(entries) and ENTRIES in kinds:
        placed, who = rows[kinds.index(ENTRIES)], rows[kinds.index(DOCUMENTS)]
        doc, place = unpack(placed["keys"])[entries], unpack(placed["places"])[entries]
        ids, marks = _read_ids(who["places"]), np.frombuffer(who["keys"], dtype="<i8")
        order = np.lexsort((place, doc))
        doc, place = doc[order], place[order]
        edges = np.r_[np.flatnonzero(np.r_[True, np.diff(doc) > 0]), len(doc)]
        out = [(ids[doc[a]], int(marks[doc[a]]), pack(place[a:b])) for a, b in zip(edges, edges[1:], strict=False)]
    cols = list(zip(*out, strict=True)) if out else [[], [], []]
    return pa.table([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.binary()), strict=True)], names=["doc_id", "mark", "places"])


def repeated_places(docs: DataFrame, emit: Callable[..., Iterator[tuple]], columns: tuple[str, ...] = ("text",), slice_bytes: int = 500_000, key_bytes: int = 8, most_entries: int = 0) -> DataFrame:
    """doc_id, mark, places (packed arrays that together hold them) of documents with places whose content is met at any other place.

    ``docs`` has doc_id, mark (a hash of the text; both name a row) and ``columns``, the text last.  ``emit`` gets
    lists of these columns' values and yields (doc, place, key, second key) arrays, a long text in several: two independent
    64-bit hashes an entry.  A bucket is a range of the first, and entries are told apart there by ``key_bytes`` of the second;
    fewer bytes than 8 suit a step whose result another one verifies, as equal keys of different content then only cost work.
    ``most_entries`` bounds the entries from above, so that the buckets' number grows with the data.
    """
    buckets = bucket_count(docs.sparkSession, most_entries)

    @lean
    def run(batches):
        uid = TaskContext.get().partitionId() << 24
        docs_in, parts, n = [], [], 0

        def rows() -> pa.RecordBatch:
            doc, place, key, second = (np.concatenate(x) for x in zip(*parts, strict=True))
            parts.clear()
            return _record(_send(uid, docs_in, key, second, doc, place, buckets, key_bytes))

        for ids, marks, *values in slices(batches, ["doc_id", "mark", *columns], slice_bytes):
            base, here = len(docs_in), list(zip(ids, marks, strict=True))
            docs_in = docs_in + here
            for doc, place, key, second in emit(*values):
                parts.append(((doc + base).astype(np.int32), place.astype(np.int64), key, second))
                n += len(key)
                if n >= BATCH_ENTRIES:  # what is left of this slice's documents goes on in the next batch
                    yield rows()
                    docs_in, base, n, uid = here, 0, 0, uid + 1
            if not n:
                docs_in = []
        if n:
            yield rows()

    def meet(table: pa.Table) -> pa.Table:
        out = _meet(table, key_bytes)
        give_back()
        return out

    sent = docs.select("doc_id", "mark", *columns).mapInArrow(run, ROWS_SQL)
    met = sent.groupBy("bucket").applyInArrow(meet, ROWS_SQL)
    found = met.groupBy("uid").applyInArrow(_gather, "doc_id long, mark long, places binary")
    return found.groupBy("doc_id", "mark").agg(F.collect_set("places").alias("places"))


def with_copies_marked(docs: DataFrame) -> DataFrame:
    """``docs`` (doc_id, text) with mark, copied (the whole text stands in more than one row) and spare (all of those but the first).

    One aggregate by a digest of the text, with partial sums, so a text that a third of the rows hold is no hot group.
    """
    slim = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    slim = slim.select("doc_id", "text", F.xxhash64("text").alias("mark"), F.unhex(F.md5("text")).alias("digest"))
    groups = slim.groupBy("digest").agg(F.min("doc_id").alias("least"), F.count(F.lit(1)).alias("rows")).where("rows > 1").select("digest", "least")
    groups = storage.small(storage.spill(groups, "copies"))
    return slim.join(groups.withColumn("copied", F.lit(True)), "digest", "left").select("doc_id", "text", "mark", F.coalesce("copied", F.lit(False)).alias("copied"), (F.coalesce("copied", F.lit(False)) & ~F.col("doc_id").eqNullSafe(F.col("least"))).alias("spare"))


def with_places(docs: DataFrame, places: DataFrame, how: str, most_keys: int = storage.BROADCAST_ROWS) -> DataFrame:
    """``docs`` with the places of each; texts of other documents are shuffled only if the list of ids is large."""
    of = places.withColumnRenamed("doc_id", "_of").withColumnRenamed("mark", "_mark")
    both = docs["doc_id"].eqNullSafe(of["_of"]) & (docs["mark"] == of["_mark"])
    if how == "inner":
        keys = storage.small(of.select("_of", "_mark"), most_keys)
        docs = docs.join(keys, docs["doc_id"].eqNullSafe(keys["_of"]) & (docs["mark"] == keys["_mark"]), "left_semi")
        both = docs["doc_id"].eqNullSafe(of["_of"]) & (docs["mark"] == of["_mark"])
    return docs.join(of, both, how).drop("_of", "_mark")


def forget_shuffles(spark) -> None:
    """Let the driver notice that shuffles of finished steps are not needed any more, so that their files go before the next step writes its own."""
    gc.collect()
    spark._jvm.System.gc()
