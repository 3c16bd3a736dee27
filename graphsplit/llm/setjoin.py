"""N-gram Jaccard join with a token-group matrix.

A document is its set of word shingles, as 64-bit hashes.  Two documents link if intersection / union reaches the threshold.

1. Documents with equal sets are one class; its least id stands for it.
2. All tokens have a global order, from rare to frequent by a counting sketch of fixed size, then by hash.  If two sets
   link, their first tokens in that order (``prefix``) share at least ``shared`` tokens.  So a document of whose first
   tokens fewer are met anywhere else links with nothing; most end here.
3. The others are partitioned into groups of similar documents, by the most frequent of their repeated first tokens.  The
   token-group matrix stores each group's union of these tokens, sparse, as (token, group) rows.
4. A join with the matrix bounds, for each query and group, how many tokens the query shares with any member; only groups that reach the
   bound are opened, and of two groups the one with the smaller name.
5. An opened group is first met through its leader, a member of median size.  What links with the leader is one component, and needs no
   more tests against it; so a large family of copies costs each of them one test.  The other queries are counted against all
   other members, and those that link with the leader against the members that do not.  Both are dealt in blocks, so no task holds a group.
   Whole sets are sent only where a link is possible: sizes and first tokens rule out most pairs with a leader, sizes most queries and members of a group.
6. Links become components; a task gives only a spanning forest of its links.

Null and empty texts have empty sets and link with nothing.  Rows with a null id are kept, link with nothing and have a null
component.  Rows that share an id are one node.  Repeated rows are one class.  Of a long text its set is held, 8 bytes a word.
An empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import repeats, storage
from .components import connected
from .textkit import BASE_A, U64, encoded, give_back, lean, mix, slices, unpack_all, window_hash, word_hashes

#: Counters of the frequency sketch (a power of two; its size does not depend on the data) and its slices.
COUNTERS, SLICES = 1 << 22, 64
#: Members and queries in one block of a group; partial sketches that one task adds up.
BLOCK, ADDED = 1500, 256


class Rule:
    """Shingle width and threshold of a join, and the prefix lengths that follow."""

    def __init__(self, width: int = 5, num: int = 80, den: int = 100):
        self.width, self.num, self.den = width, num, den

    def tokens(self, text: str | None) -> np.ndarray:
        """Distinct shingles, ascending by hash; a text with fewer words than the width is one shingle."""
        words = encoded(text).lower().split()
        if not words:
            return np.zeros(0, dtype=U64)
        hashes = word_hashes(words)
        if len(words) < self.width:
            return mix(window_hash(hashes, len(words), BASE_A) + U64(len(words)))
        return np.unique(window_hash(hashes, self.width, BASE_A))

    def overlap(self, n: int) -> int:
        """Tokens that a set of n shares with any set it links with, at least."""
        return -(-self.num * n // self.den)

    def shared(self, n: int) -> int:
        """Tokens of the prefix that are shared, if the other set is no smaller."""
        return (n - self.overlap(n)) // 2 + 1

    def needed(self, n: int) -> int:
        """The same for any partner; the smallest has overlap(n) tokens."""
        return self.shared(self.overlap(n))

    def prefix(self, n: int) -> int:
        return min(n, n - self.overlap(n) + self.shared(n))

    def links(self, both, n, m):
        return both * self.den >= self.num * (n + m - both)

    # The same as columns of a table.
    def shared_of(self, n: Column) -> Column:
        return F.floor((n - F.ceil(n * self.num / self.den)) / 2) + 1

    def alike(self, n: Column, m: Column) -> Column:
        """Whether sets of n and m tokens may link by their sizes."""
        return F.least(n, m) * self.den >= F.greatest(n, m) * self.num

    def pair_shared(self, n: Column, m: Column) -> Column:
        """Tokens that the prefixes of linked sets of n and m share, at least.

        Such sets share ``both`` tokens.  The first l of these in the global order have both - l behind them, so they are among a
        set's first n - both + l: within its prefix, if l is at most both less the tokens behind the prefix.
        """
        both = F.ceil((n + m) * self.num / (self.num + self.den))
        behind = lambda k: F.greatest(F.lit(0), F.ceil(k * self.num / self.den) - self.shared_of(k))
        return both - F.greatest(behind(n), behind(m))


# ---------------------------------------------------------------- sets and the sketch

def sets_and_sketch(docs: DataFrame, rule: Rule) -> tuple[DataFrame, bytes]:
    """(doc_id, n_shingles, digest) of each row, and how frequent each counter's tokens are, one byte a counter.

    Partial sketches are added up in a tree, ``ADDED`` at a time, so no task's work grows with the number of tasks.
    """
    per = COUNTERS // SLICES

    @lean
    def run(batches):
        counts = np.zeros(COUNTERS, dtype=np.int32)
        for ids, texts in slices(batches, ["doc_id", "text"], 1_000_000):
            sets = [rule.tokens(t) for t in texts]
            slot, times = np.unique((np.concatenate(sets) & U64(COUNTERS - 1)).astype(np.int32), return_counts=True)
            counts[slot] += times.astype(np.int32)
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array([len(s) for s in sets], pa.int64()), pa.array([xxhash.xxh3_128_digest(s.tobytes()) for s in sets], pa.binary()), pa.nulls(len(ids), pa.int32()), pa.nulls(len(ids), pa.int64())], ["doc_id", "n_shingles", "digest", "slice", "part"])
        if counts.any():
            blobs = [zstandard.compress(counts[k * per : (k + 1) * per].astype(np.int64).tobytes(), 1) for k in range(SLICES)]
            yield pa.RecordBatch.from_arrays([pa.nulls(SLICES, pa.int64()), pa.nulls(SLICES, pa.int64()), pa.array(blobs, pa.binary()), pa.array(range(SLICES), pa.int32()), pa.array([TaskContext.get().partitionId()] * SLICES, pa.int64())], ["doc_id", "n_shingles", "digest", "slice", "part"])

    both = storage.spill(docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_shingles long, digest binary, slice int, part long"), "sets")

    def add(table: pa.Table) -> pa.Table:
        total = np.zeros(per, dtype=np.int64)
        for blob in table.column("digest").to_pylist():
            total += np.frombuffer(zstandard.decompress(blob), dtype=np.int64)
        return pa.table({"slice": table.column("slice").slice(0, 1), "part": table.column("part").slice(0, 1), "digest": pa.array([zstandard.compress(total.tobytes(), 1)], pa.binary())})

    partial = both.where("slice is not null").select("slice", "part", "digest")
    parts = (partial.agg(F.max("part")).first()[0] or 0) + 1
    while True:
        partial = partial.withColumn("part", F.expr(f"part div {ADDED}")).groupBy("slice", "part").applyInArrow(add, "slice int, part long, digest binary")
        parts = -(-parts // ADDED)
        if parts == 1:
            break
    found = {r["slice"]: np.frombuffer(zstandard.decompress(bytes(r["digest"])), dtype=np.int64) for r in partial.collect()}
    level = lambda k: np.minimum(255, 4 * np.log2(1 + found[k])).astype(np.uint8).tobytes() if k in found else bytes(per)
    return both.where("slice is null").drop("slice", "part"), b"".join(map(level, range(SLICES)))


# ---------------------------------------------------------------- first tokens

def first_tokens(tokens: np.ndarray, levels: np.ndarray, rule: Rule) -> np.ndarray:
    """The prefix of a set in the global order, from rare to frequent."""
    order = np.lexsort((tokens, levels[(tokens & U64(COUNTERS - 1)).astype(np.int64)]))
    return tokens[order[: rule.prefix(len(tokens))]]


def key_emitter(sketch: bytes, rule: Rule):
    def emit(texts):
        levels = np.frombuffer(sketch, dtype=np.uint8)
        keys = [first_tokens(s, levels, rule) if len(s) else s for s in map(rule.tokens, texts)]
        size = np.array([len(k) for k in keys], dtype=np.int64)
        every = np.concatenate(keys) if keys else np.zeros(0, dtype=U64)
        place = np.arange(len(every)) - np.repeat(np.cumsum(size) - size, size)
        yield np.repeat(np.arange(len(keys)), size), place, mix(every + U64(1)), mix(every ^ U64(0xA0761D6478BD642F))

    return emit


def enough_places(places: DataFrame, sizes: DataFrame, rule: Rule) -> DataFrame:
    """``places`` without rows of fewer repeated first tokens than any link of a set of n tokens needs; ``sizes`` has doc_id, n, the least of its rows.

    Only ids, counts and packed places are shuffled, so the texts of what ends here need not be.
    """

    def run(batches):
        for batch in batches:
            again = [len(unpack_all(p)) for p in batch.column("places").to_pylist()]
            keep = [k >= rule.needed(n) for k, n in zip(again, batch.column("n").to_pylist(), strict=True)]
            yield batch.filter(pa.array(keep, pa.bool_())).select(["doc_id", "mark", "places"])

    return places.join(sizes, "doc_id").select("doc_id", "mark", "places", "n").mapInArrow(run, places.schema)


def survivors(docs: DataFrame, places: DataFrame, sketch: bytes, rule: Rule) -> DataFrame:
    """doc_id, n, keys (repeated first tokens), grp and the whole set of documents that may link."""
    schema = "doc_id long, n long, keys array<long>, grp long, tokens binary"

    @lean
    def run(batches):
        levels = np.frombuffer(sketch, dtype=np.uint8)
        for ids, packed, texts in slices(batches, ["doc_id", "places", "text"]):
            rows = []
            for doc, p, text in zip(ids, packed, texts, strict=True):
                tokens = rule.tokens(text)
                again = unpack_all(p)
                if len(again) >= rule.needed(len(tokens)):
                    keys = first_tokens(tokens, levels, rule)[again].astype(np.int64)
                    rows.append((doc, len(tokens), keys, int(keys[-1]), tokens.tobytes()))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.int64(), pa.binary()), strict=True)], ["doc_id", "n", "keys", "grp", "tokens"])

    return repeats.with_places(docs, storage.small(places), "inner", 4 * storage.BROADCAST_ROWS).select("doc_id", "places", "text").mapInArrow(run, schema)


# ---------------------------------------------------------------- the matrix and the groups

def sized(found: DataFrame) -> DataFrame:
    """(doc_id, n, keys, grp, members) of survivors; members is the size of the group."""
    slim = found.select("doc_id", "n", "keys", "grp")
    sizes = storage.spill(slim.groupBy("grp").agg(F.count(F.lit(1)).alias("members")), "sizes")
    return slim.join(storage.small(sizes), "grp")


def token_groups(slim: DataFrame) -> DataFrame:
    """The token-group matrix: (token, of, of_members), each group's union of its members' repeated first tokens."""
    return slim.select(F.col("grp").alias("of"), F.col("members").alias("of_members"), F.explode("keys").alias("token")).distinct()


def opened(slim: DataFrame, matrix: DataFrame, rule: Rule) -> DataFrame:
    """(doc_id, n, grp): of the groups larger than the query's own, those whose union holds enough of the query's first tokens.

    Groups are ordered by size, then by name: few queries go from small groups to large ones, not the other way.
    """
    entries = slim.select("doc_id", "n", "grp", "members", F.explode("keys").alias("token"))
    needed = rule.shared_of(F.ceil(F.col("n") * rule.num / rule.den))
    met = entries.join(matrix, "token").where(F.struct(F.col("of_members"), F.col("of")) > F.struct(F.col("members"), F.col("grp")))
    held = met.groupBy("doc_id", "n", F.col("of").alias("grp")).agg(F.count(F.lit(1)).alias("held"))
    return held.where(F.col("held") >= needed).select("doc_id", "n", "grp").distinct()


def leaders(slim: DataFrame) -> DataFrame:
    """(grp, lead, lead_n, sole, lead_keys): a member of median size of each group, and whether it has one set there."""
    mid = slim.groupBy("grp").agg(F.percentile_approx("n", 0.5).alias("mid"))
    near = F.struct(F.abs(F.col("n") - F.col("mid")), "doc_id")
    each = slim.groupBy("grp", "doc_id").agg(F.min("n").alias("n"), F.count(F.lit(1)).alias("sets"))
    lead = each.join(storage.small(storage.spill(mid, "mid")), "grp").groupBy("grp").agg(F.min_by(F.struct("doc_id", "n", "sets"), near).alias("least"))
    lead = lead.select("grp", F.col("least.doc_id").alias("lead"), F.col("least.n").alias("lead_n"), (F.col("least.sets") == 1).alias("sole"))
    keys = slim.select("grp", F.col("doc_id").alias("lead"), F.col("n").alias("lead_n"), F.col("keys").alias("lead_keys"))
    return keys.join(storage.small(storage.spill(lead, "lead")), ["grp", "lead", "lead_n"])


def ruled_out(queries: DataFrame, lead: DataFrame, rule: Rule) -> DataFrame:
    """(doc_id, n, grp, home, lead, lead_n, sole, linked) of queries (doc_id, n, keys, grp, home); linked is null where the whole sets have to be compared.

    A first token that two sets share is a repeated one, so ``keys`` hold all of them.
    """
    itself = F.col("home") & (F.col("doc_id") == F.col("lead"))
    common = F.size(F.array_intersect("keys", "lead_keys"))
    far = ~rule.alike(F.col("n"), F.col("lead_n")) | (common < rule.pair_shared(F.col("n"), F.col("lead_n")))
    linked = F.when(itself, F.lit(True)).when(far, F.lit(False))
    return queries.join(storage.small(lead), "grp").select("doc_id", "n", "grp", "home", "lead", "lead_n", "sole", linked.alias("linked"))


def against_leaders(pairs: DataFrame, rule: Rule) -> DataFrame:
    """(doc_id, n, grp, home, lead, sole, linked) of queries (doc_id, n, grp, home, lead, sole, tokens, lead_set)."""
    kept = ["doc_id", "n", "grp", "home", "lead", "sole"]

    @lean
    def run(batches):
        for batch in batches:
            linked = []
            for own, lead in zip(batch.column("tokens").to_pylist(), batch.column("lead_set").to_pylist(), strict=True):
                a, b = np.frombuffer(own, dtype=U64), np.frombuffer(lead, dtype=U64)
                least = min(len(a), len(b)) * rule.den >= rule.num * max(len(a), len(b))
                linked.append(bool(least and rule.links(len(np.intersect1d(a, b, assume_unique=True)), len(a), len(b))))
            yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in kept], pa.array(linked)], [*kept, "linked"])

    return pairs.select(*kept, "tokens", "lead_set").mapInArrow(run, "doc_id long, n long, grp long, home boolean, lead long, sole boolean, linked boolean")


def may_meet(rows: DataFrame, others: DataFrame, own: Column, rule: Rule) -> DataFrame:
    """``rows`` (n, grp, side, ...) that may link, by their sizes, with a row of ``others`` but themselves; ``own``: whether a row is one of the others."""
    seen = others.groupBy("grp", "side").agg(F.count(F.lit(1)).alias("_rows"), F.min("n").alias("_least"), F.max("n").alias("_most"))
    seen = storage.small(storage.spill(seen, "lengths"))
    n, least, most = F.col("n"), F.col("_least"), F.col("_most")
    between = (most * rule.den >= n * rule.num) & (n * rule.den >= least * rule.num)
    some = F.when(own & (F.col("_rows") == 1), F.lit(False)).when(own & (F.col("_rows") == 2), rule.alike(n, least + most - n)).otherwise(between)
    return rows.join(seen, ["grp", "side"]).where(some).select(*rows.columns)


def _verify(table: pa.Table, rule: Rule) -> pa.Table:
    """One block: exact links between its queries and its members, as a spanning forest (a, b)."""
    role = table.column("role").to_numpy()
    docs = table.column("doc_id").to_numpy()
    sets = [np.frombuffer(t, dtype=U64) for t in table.column("tokens").to_pylist()]
    members, queries = np.flatnonzero(role == 0), np.flatnonzero(role == 1)
    edges: dict[int, int] = {}

    def find(x: int) -> int:
        while (up := edges.get(x, x)) != x:
            edges[x] = x = edges.get(up, up)
        return x

    if len(members) and len(queries):
        size = np.array([len(sets[m]) for m in members], dtype=np.int64)
        every = np.concatenate([sets[m] for m in members])
        owner = np.repeat(np.arange(len(members)), size)
        order = np.argsort(every, kind="stable")
        every, owner = every[order], owner[order]
        union, starts, counts = np.unique(every, return_index=True, return_counts=True)
        for q in queries.tolist():
            own = sets[q]
            at = np.searchsorted(union, own)
            at = at[(at < len(union)) & (union[np.minimum(at, len(union) - 1)] == own)]
            if len(at) < rule.overlap(len(own)):
                continue  # the group's union rules it out
            c = counts[at]
            where = np.repeat(starts[at] - np.cumsum(c) + c, c) + np.arange(c.sum())
            both = np.bincount(owner[where], minlength=len(members))
            for m in docs[members[rule.links(both, len(own), size)]].tolist():
                a, b = find(int(docs[q])), find(m)
                if a != b:
                    edges[max(a, b)] = min(a, b)
    pairs = [(a, b) for a, b in edges.items() if a != b]
    return pa.table([pa.array([p[k] for p in pairs], pa.int64()) for k in (0, 1)], names=["a", "b"])


def links(found: DataFrame, rule: Rule) -> DataFrame:
    """Edges (a, b) that span what is linked among the survivors."""
    slim = storage.spill(sized(found), "sized")
    matrix = storage.spill(token_groups(slim), "matrix")
    asked = storage.spill(opened(slim, matrix, rule), "opened")
    several = slim.where("members > 1")
    wanted = storage.small(storage.spill(several.select("grp").unionByName(asked.select("grp")).distinct(), "wanted"))
    lead = storage.spill(leaders(slim.join(wanted, "grp", "left_semi")), "leaders")
    cols = ("doc_id", "n", "keys", "grp")
    queries = several.select(*cols, F.lit(True).alias("home")).unionByName(slim.drop("grp").join(storage.small(asked), ["doc_id", "n"]).select(*cols, F.lit(False).alias("home")))
    asks = storage.spill(ruled_out(queries, lead, rule), "asks")
    unsure = asks.where("linked is null")
    sets = found.select("doc_id", "n", "tokens")
    compared = storage.small(storage.spill(unsure.select("grp", "lead", "lead_n").distinct(), "compared"))
    lead_sets = found.select("grp", F.col("doc_id").alias("lead"), F.col("n").alias("lead_n"), F.col("tokens").alias("lead_set")).join(compared, ["grp", "lead", "lead_n"]).select("grp", "lead_set")
    pairs = sets.join(storage.small(unsure.drop("linked", "lead_n")), ["doc_id", "n"]).join(storage.small(lead_sets), "grp")
    tried = against_leaders(pairs, rule).unionByName(asks.where("linked is not null").drop("lead_n"))
    tried = storage.spill(tried, "tried")
    storage.release(slim, matrix, lead, asks)
    near = tried.where("linked and doc_id <> lead").select(F.col("doc_id").alias("a"), F.col("lead").alias("b"))
    # Side 0 of a group: members that link with its leader, which all queries have met; side 1: the others.  Who links with the leader need not meet side 0.
    every = F.explode(F.array(F.lit(0), F.lit(1)))
    queries = tried.where("not linked").select("doc_id", "n", "grp", "home", every.alias("side")).unionByName(tried.where("linked and not home").select("doc_id", "n", "grp", "home", F.lit(1).alias("side")))
    members = tried.where("home and not (linked and sole and doc_id = lead)").select("doc_id", "n", "grp", (~F.col("linked")).cast("int").alias("side"))
    queries = may_meet(queries, members, F.col("home") & (F.col("side") == 1), rule)
    members = may_meet(members, queries, F.lit(False), rule)
    blocks = lambda n: F.greatest(F.lit(1), F.ceil(n / F.lit(BLOCK))).cast("int")
    size = members.groupBy("grp", "side").agg(blocks(F.count(F.lit(1))).alias("mb")).join(queries.groupBy("grp", "side").agg(blocks(F.count(F.lit(1))).alias("qb")), ["grp", "side"])
    size = storage.small(storage.spill(size, "sides"))
    deal = lambda n: F.pmod(F.xxhash64("doc_id"), n).cast("int")
    spread = lambda n: F.explode(F.sequence(F.lit(0), n - 1))
    both = members.join(size, ["grp", "side"]).select("doc_id", "n", "grp", "side", deal(F.col("mb")).alias("mblock"), spread(F.col("qb")).alias("qblock"), F.lit(0).alias("role"))
    both = both.unionByName(queries.join(size, ["grp", "side"]).select("doc_id", "n", "grp", "side", spread(F.col("mb")).alias("mblock"), deal(F.col("qb")).alias("qblock"), F.lit(1).alias("role")))
    both = sets.join(storage.small(storage.spill(both, "dealt")), ["doc_id", "n"])

    def run(table: pa.Table) -> pa.Table:
        out = _verify(table, rule)
        give_back()
        return out

    return near.unionByName(both.groupBy("grp", "side", "mblock", "qblock").applyInArrow(run, "a long, b long"))


def components(docs: DataFrame, rule: Rule) -> DataFrame:
    """doc_id, n_shingles, component_id for each row of ``docs`` (doc_id, text)."""
    spark = docs.sparkSession
    sets, sketch = sets_and_sketch(docs, rule)
    classes = sets.where("n_shingles > 0 and doc_id is not null").groupBy("digest").agg(F.min("doc_id").alias("rep"))
    classes = storage.spill(classes, "classes")
    reps = storage.small(classes.select("rep").distinct(), 2 * storage.BROADCAST_ROWS)
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    marked = docs.select("doc_id", "text", F.xxhash64(F.coalesce("text", F.lit(""))).alias("mark"))
    own = marked.join(reps, marked["doc_id"] == reps["rep"], "left_semi")
    places = storage.spill(repeats.repeated_places(own, key_emitter(sketch, rule), key_bytes=5, most_entries=size // 12), "keys")
    repeats.forget_shuffles(spark)
    valid = sets.where("n_shingles > 0 and doc_id is not null")
    few, places = places, storage.spill(enough_places(places, valid.groupBy("doc_id").agg(F.min("n_shingles").alias("n")), rule), "enough")
    storage.release(few)
    # Ids of several rows; their sets are kept once each.
    ids = storage.spill(valid.groupBy("doc_id").agg(F.count(F.lit(1)).alias("rows"), F.count_distinct("digest").alias("k")).where("rows > 1"), "ids")
    found = survivors(marked, places, sketch, rule)  # places name rows of ``own`` only
    if ids.take(1):
        several = storage.small(ids.select("doc_id"))
        found = found.join(several, "doc_id", "left_anti").unionByName(found.join(several, "doc_id", "left_semi").dropDuplicates(["doc_id", "tokens"]))
    found = storage.spill(found, "survivors")
    storage.release(places)
    edges = storage.spill(links(found, rule), "links")
    # Rows that share an id are one node: tie the classes they are in.
    shared = valid.join(classes, "digest").where("doc_id <> rep").select(F.col("doc_id").alias("a"), F.col("rep").alias("b"))
    tied = shared.join(storage.small(ids.where("k > 1").select(F.col("doc_id").alias("a"))), "a", "left_semi")
    label = connected(edges.unionByName(tied))
    storage.release(found, edges)
    out = sets.join(classes, "digest", "left")
    rep = F.when((F.col("n_shingles") > 0) & F.col("doc_id").isNotNull(), F.col("rep")).otherwise(F.col("doc_id"))
    out = out.select("doc_id", "n_shingles", rep.alias("rep"))
    return out.join(storage.small(label), out["rep"] == label["node"], "left").select("doc_id", "n_shingles", F.coalesce("component", "rep").alias("component_id"))


def keep_one(docs: DataFrame, rule: Rule) -> DataFrame:
    """``docs`` without all rows of a component but the one of least id; rows of a null id, or without words, stay."""
    found = components(docs.select("doc_id", "text"), rule)
    gone = found.where("component_id <> doc_id").select(F.col("doc_id").alias("_gone")).distinct()
    gone = storage.small(storage.spill(gone, "gone"))
    return docs.join(gone, docs["doc_id"] == gone["_gone"], "left_anti")


def op4_jaccard(spark, sf_dir: str) -> DataFrame:
    return components(storage.table(spark, sf_dir, "documents").select("doc_id", "text"), Rule(3, 90, 100))


ORACLE = r"""
WITH RECURSIVE d AS (SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 3 THEN [array_to_string(w, ' ')] ELSE [w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] FOR i IN range(1, len(w) - 1)] END) AS g FROM d),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
c AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS shared FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
l AS (SELECT x, y FROM c JOIN n a ON a.doc_id = x JOIN n b ON b.doc_id = y WHERE 100 * shared >= 90 * (a.n + b.n - shared)),
e AS (SELECT x, y FROM l UNION ALL SELECT y, x FROM l),
r AS (SELECT doc_id, doc_id AS c FROM d UNION SELECT e.y, r.c FROM r JOIN e ON e.x = r.doc_id WHERE r.c < e.y)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, m.c AS component_id FROM d LEFT JOIN n USING (doc_id) JOIN (SELECT doc_id, min(c) AS c FROM r GROUP BY 1) m USING (doc_id)
"""
