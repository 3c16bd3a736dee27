"""Best-fit packing of token sequences, with certified bin counts and repacking of the partitions that have a gap.

1. ``token_pieces`` tokenises whole texts and cuts only what is longer than a sequence.
2. ``pack_pieces`` deals the pieces to partitions, packs each by best-fit decreasing and certifies its bin
   count by lower bounds from dual-feasible functions.  Partitions whose count is above the bound give the pieces
   of their unfilled bins to a common pool, which is dealt and packed anew; rounds end when they save nothing.

Pieces with null ids, repeated rows and empty texts are packed like any other: an empty or null text is the one
closing id.  Ties are ordered by length, doc_id, piece.  An empty table gives an empty result.
"""

from __future__ import annotations

import bisect
import json
import zlib
from array import array

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import storage
from .bytebpe import byte_characters
from .textkit import BoundedCache, lean, slices, word_chunks, worker_cache

SEQUENCE = 2048
#: Pieces in one partition of the packing step; a partition is one task's work.
PARTITION_PIECES = 25_000
#: Most rounds of repacking.
ROUNDS = 4

PIECES = T.StructType([
    T.StructField("doc_id", T.LongType()), T.StructField("piece", T.IntegerType()), T.StructField("start", T.LongType()),
    T.StructField("length", T.LongType()), T.StructField("ids_crc32", T.LongType()),
])


# ---------------------------------------------------------------- tokenising

#: Fixed value: the pattern that the library's byte-level pre-tokenizer splits by.
BYTE_LEVEL = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


def merges_by_rank(blob: bytes, pattern: str) -> bool:
    """Whether merging the pair of lowest id first gives the library's ids on every text.

    The library merges listed pairs in the order of the list; a rank encoder merges any two neighbours whose string is a token.  If ids
    rise along the list and the library's model makes each token's string into that token alone, then no unlisted pair can ever be the next
    one: where two neighbours spell a token and nothing of lower rank is left, the same steps happen inside that token's own string,
    and there they end in its listed pair.
    """
    from tokenizers import Tokenizer

    spec, library = json.loads(blob), Tokenizer.from_str(blob.decode())
    model, split = spec["model"], spec.get("pre_tokenizer") or {}
    plain = model["type"] == "BPE" and not any(model.get(x) for x in ("dropout", "unk_token", "continuing_subword_prefix", "end_of_word_suffix", "byte_fallback", "ignore_merges"))
    if not plain or spec.get("normalizer") or split.get("type") != "ByteLevel" or split.get("add_prefix_space") or not split.get("use_regex", True) or pattern != BYTE_LEVEL:
        return False
    vocab = model["vocab"]
    made = [vocab.get("".join(m if isinstance(m, list) else m.split(" "))) for m in model["merges"]]
    if None in made or any(a >= b for a, b in zip(made, made[1:], strict=False)) or not set(byte_characters()) <= vocab.keys():
        return False
    return all([t.id for t in library.model.tokenize(token)] == [i] for token, i in vocab.items())


class ChunkEncoder:
    """Ids of texts by a ``tokenizers`` file, four little-endian bytes an id.

    A byte-level pre-tokenizer starts a new piece at each single blank between two other characters, so what
    stands between two such blanks is encoded once and kept.  Where ``merges_by_rank`` holds for the file, new chunks go through a rank
    encoder built from the same vocabulary, which gives the same ids faster; else, and for texts with an added token's string, the library encodes.
    """

    def __init__(self, blob: bytes, pattern: str, by_rank: bool):
        import tiktoken
        from tokenizers import Tokenizer

        self.model = Tokenizer.from_str(blob.decode())
        added = {t.content for t in self.model.get_added_tokens_decoder().values()}
        self.special = sorted(added)
        self.ranked = None
        if by_rank:
            to_byte = {c: b for b, c in enumerate(byte_characters())}
            ranks = {bytes(to_byte[c] for c in token): i for token, i in self.model.get_vocab(with_added_tokens=False).items() if token not in added}
            self.ranked = tiktoken.Encoding("ranked", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
            self.blob, self.model = blob, None  # made again if a text needs it
        self.known = BoundedCache(40 << 20)

    def library(self, texts: list[str]) -> list[bytes]:
        if self.model is None:
            from tokenizers import Tokenizer

            self.model = Tokenizer.from_str(self.blob.decode())
        return [np.array(e.ids, dtype="<u4").tobytes() for e in self.model.encode_batch_fast(texts, add_special_tokens=False)]

    def _new(self, chunks: list[str]) -> list[bytes]:
        if self.ranked is None:
            return self.library(chunks)
        return [array("I", ids).tobytes() for ids in map(self.ranked.encode_ordinary, chunks)]

    def encode(self, texts: list[str]) -> list[bytes]:
        cut = [None if any(s in t for s in self.special) else word_chunks(t) for t in texts]
        known = self.known
        missing = list({c for cs in cut if cs is not None for c in cs if c not in known})
        fresh = dict(zip(missing, self._new(missing), strict=True))
        known.keep(fresh.items())
        long = {c for c in missing if len(c) > known.LONGEST}
        out = []
        for t, cs in zip(texts, cut, strict=True):
            if cs is None:
                out.append(self.library([t])[0])
            elif long and not long.isdisjoint(cs):
                out.append(b"".join([fresh[c] if c in fresh else known[c] for c in cs]))
            else:
                out.append(b"".join(map(known.__getitem__, cs)))
        known.tidy()
        return out


def cut_lengths(n: int, most: int) -> list[int]:
    """Lengths of a document's pieces: whole sequences, after a first piece that takes the rest."""
    whole, rest = divmod(n, most)
    return ([rest] if rest else []) + [most] * whole


def token_pieces(docs: DataFrame, vocabulary: bytes, pattern: str, end_id: int = 0, most: int = SEQUENCE) -> DataFrame:
    """Rows of PIECES from doc_id and text; one task reads and encodes its own rows, nothing is shuffled."""

    by_rank = merges_by_rank(vocabulary, pattern)
    storage.modest_batches(docs.sparkSession)

    @lean
    def run(batches):
        cache = worker_cache("packing")
        if "encoder" not in cache:
            cache["encoder"] = ChunkEncoder(vocabulary, pattern, by_rank)
        encoder, end = cache["encoder"], np.array([end_id], dtype="<u4").tobytes()
        for ids, texts in slices(batches, ["doc_id", "text"], 1_000_000):
            rows = []
            for doc, code in zip(ids, encoder.encode([t or "" for t in texts]), strict=True):
                code += end
                at = 0
                for k, n in enumerate(cut_lengths(len(code) // 4, most)):
                    rows.append((doc, k, at, n, zlib.crc32(code[4 * at : 4 * (at + n)])))
                    at += n
            cols = list(zip(*rows, strict=True))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()), strict=True)], PIECES.names)

    return docs.select("doc_id", "text").mapInArrow(run, PIECES)


# ---------------------------------------------------------------- packing

def best_fit(lengths: np.ndarray, most: int) -> np.ndarray:
    """Bin of each item, items taken by falling length, each into the fullest bin that has room."""
    order = np.argsort(-lengths, kind="stable")
    out = np.empty(len(lengths), dtype=np.int64)
    rooms: list[int] = []  # distinct free rooms, ascending
    bins: dict[int, list[int]] = {}
    n = 0
    for i in order.tolist():
        need = int(lengths[i])
        k = bisect.bisect_left(rooms, need)
        if k == len(rooms):
            b, room = n, most
            n += 1
        else:
            room = rooms[k]
            b = bins[room].pop()
            if not bins[room]:
                del bins[room], rooms[k]
        out[i] = b
        left = room - need
        if left:
            if left not in bins:
                bins[left] = []
                bisect.insort(rooms, left)
            bins[left].append(b)
    return out


def lower_bound(lengths: np.ndarray, most: int) -> int:
    """Bins that any packing needs: the best of two families of dual-feasible functions over the length counts.

    f_e counts items over most - e as whole bins and drops those under e; g_k rounds x * (k + 1) / most down, but leaves exact
    multiples as they are.  For either, the function's sum over what fits one bin is at most 1.
    """
    if not len(lengths):
        return 0
    size, count = np.unique(lengths, return_counts=True)
    best = -(-int((size * count).sum()) // most)
    for e in np.unique(np.concatenate([size[size <= most // 2], most - size[size > most // 2]])):
        w = np.where(size > most - e, most, np.where(size < e, 0, size))
        best = max(best, -(-int((w * count).sum()) // most))
    for k in range(1, 25):
        scaled = size * (k + 1)
        w = np.where(scaled % most == 0, scaled // most * k, (scaled // most) * (k + 1))  # in units of 1 / (k (k + 1))
        best = max(best, -(-int((w * count).sum()) // (k * (k + 1))))
    return best


def _packed(items: pa.Table, most: int) -> pa.Table:
    """One partition, packed: its rows in a fixed order with bin, offset, the bin's free room and the partition's gap."""
    items = items.take(pc.sort_indices(items, [("length", "descending"), ("doc_id", "ascending"), ("piece", "ascending"), ("ids_crc32", "ascending")]))
    lengths = items.column("length").to_numpy()
    bins = best_fit(lengths, most)
    fill = np.bincount(bins, weights=lengths).astype(np.int64)
    gap = len(fill) - lower_bound(lengths, most)
    order = np.argsort(bins, kind="stable")
    before = np.cumsum(lengths[order]) - lengths[order]
    first = np.r_[True, np.diff(bins[order]) > 0]
    offset = np.empty(len(lengths), dtype=np.int64)
    offset[order] = before - np.repeat(before[first], np.bincount(bins))
    for name, values in (("bin", bins), ("offset", offset), ("room", most - fill[bins]), ("gap", np.full(len(lengths), gap, dtype=np.int64))):
        items = items.append_column(name, pa.array(values))
    return items


def pack_pieces(pieces: DataFrame, most: int = SEQUENCE, partition_pieces: int = PARTITION_PIECES, rounds: int = ROUNDS) -> DataFrame:
    """``pieces`` with sequence_id, offset and the certificate columns round, gap (of the last round's partition).

    Pieces that fill a sequence alone are placed without any shuffle.  A partition holds about ``partition_pieces``
    pieces, dealt by a hash of their row in the written table, so equal rows are spread like any others.
    """
    cols = PIECES.names
    schema = T.StructType([*PIECES.fields, T.StructField("part", T.LongType()), *[T.StructField(c, T.LongType()) for c in ("bin", "offset", "room", "gap")]])

    def run(items: pa.Table) -> pa.Table:
        return _packed(items, most)

    pieces = storage.spill(pieces.select(*cols), "pieces")
    full = pieces.where(F.col("length") == most).select(*cols, F.lit(0).alias("round"), F.lit(0).cast("long").alias("part"), F.lit(0).cast("long").alias("bin"), F.lit(0).cast("long").alias("offset"), F.lit(0).cast("long").alias("gap"))
    pool, done, spent = pieces.where(F.col("length") < most), [], []
    for r in range(rounds):
        n = pool.count()
        if not n:
            break
        parts = max(1, round(n / partition_pieces))
        dealt = pool.withColumn("part", F.pmod(F.xxhash64(F.monotonically_increasing_id(), F.lit(r)), F.lit(parts)))
        packed = storage.spill(dealt.groupBy("part").applyInArrow(run, schema), f"packed{r}")
        spent.append(packed)
        # What stays: all bins of certified partitions, and filled bins of the others.
        again = (F.col("gap") > 0) & (F.col("room") > most // 64)
        stats = packed.agg(F.sum(again.cast("long")), F.sum((again & (F.col("offset") == 0)).cast("long")), F.sum(F.when(again, F.col("length")))).first()
        spare = (stats[1] or 0) - -(-(stats[2] or 0) // most)
        last = r == rounds - 1 or not spare or parts == 1
        kept = packed if last else packed.where(~again)
        done.append(kept.select(*cols, F.lit(r + 1).alias("round"), "part", "bin", "offset", "gap"))
        if last:
            break
        pool = packed.where(again).select(*cols)
    out = full.select(*cols, "round", "part", "bin", "offset", "gap")
    for d in done:
        out = out.unionByName(d)
    # Any number may name a sequence: a negative row number for a piece that fills one, else round, partition and bin.
    name = F.when(F.col("round") == 0, -1 - F.monotonically_increasing_id()).otherwise(F.col("round") * F.lit(1 << 56) + F.col("part") * F.lit(1 << 20) + F.col("bin"))
    return out.select(*cols, name.alias("sequence_id"), "offset", "round", "gap")


def op9_pack(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    with open(public_tokenizers.path("byte_bpe_50k.json"), "rb") as f:
        vocabulary = f.read()
    return pack_pieces(token_pieces(storage.table(spark, sf_dir, "documents"), vocabulary, public_tokenizers.PATTERN))
