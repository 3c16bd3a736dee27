"""Embedding near-duplicates with a pivot-permutation index.

1. Equal vectors are one class with a count; its least id stands for it.
2. Pivots are reference vectors from a bounded sample, no two of them close; their number grows with the square root of the vectors'.
   A vector's permutation is its ``NEAREST`` pivots in order of nearness.  The inverted index has a list for each two pivots:
   the vectors that have both among their nearest.  With so many pivots the lists stay short, however many vectors there are.
3. Lists hold permutations only, no vectors.  Inside a list, shared pivots are counted with weights that fall with their place in
   either order, and a pair is a candidate if the count reaches ``SHARED`` of what equal permutations give.  A pair that stands together
   in several lists is looked at in the list of its two least common pivots only, so counts need no pair table.
4. Vectors go only to lists in which they have a candidate, and candidates are verified there by exact cosines in double precision.
   Long lists are dealt in pairs of blocks; a task gives sums a vector and a spanning forest, never pairs.

Every vector is indexed; what shares fewer than two nearest pivots, or in too different an order, is missed
(``recall_against_brute_force`` measures it).  Vectors that are null, empty, zero, or hold null or non-finite components link with
nothing; shorter vectors count as padded with zeros.  Rows of a null id link with nothing and have a null component.  Repeated rows are
one class, each with its own row in the result; rows that share an id are one node.  An empty table gives an empty result.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import storage
from .components import connected
from .textkit import give_back, lean

#: Reference vectors: at least, and for each square root of a vector; nearest ones that describe a vector; sampled rows for each
#: reference vector; cosine above which two are too close; share of the weighted count of equal permutations that a candidate has.
PIVOTS, PIVOTS_PER_ROOT, NEAREST, SAMPLED, APART, SHARED = 256, 4, 7, 8, 0.6, 0.3
#: Members in one block of a list, members compared at once, and postings in one bucket of lists.
BLOCK, TILE, BUCKET = 2000, 400, 250_000
LINK = 0.95


def choose_pivots(sample: np.ndarray, most: int = PIVOTS, apart: float = APART) -> np.ndarray:
    """Unit rows of the sample, in its order, none closer to an earlier choice than ``apart``."""
    chosen = np.zeros((0, sample.shape[1]))
    for x in sample:
        if not len(chosen) or (chosen @ x).max() < apart:
            chosen = np.vstack([chosen, x])
        if len(chosen) == most:
            break
    return chosen


def units(rows: list, dim: int) -> np.ndarray:
    """Unit rows of vectors that are padded with zeros."""
    if all(len(r) == dim for r in rows):
        out = np.array(rows, dtype=float).reshape(-1, dim)
    else:
        out = np.zeros((len(rows), dim))
        for i, r in enumerate(rows):
            out[i, : len(r)] = r
    # Scaled first, so that squares of very large or small components stay finite.
    out /= np.abs(out).max(axis=1, keepdims=True)
    return out / np.linalg.norm(out, axis=1, keepdims=True)


def permutations(vectors: np.ndarray, pivots: np.ndarray, nearest: int = NEAREST) -> np.ndarray:
    """Numbers of the nearest pivots, nearest first."""
    k = min(nearest, len(pivots))
    near = -(vectors @ pivots.T)
    part = np.argpartition(near, k - 1, axis=1)[:, :k] if k < len(pivots) else np.tile(np.arange(k), (len(vectors), 1))
    return np.take_along_axis(part, np.argsort(np.take_along_axis(near, part, axis=1), axis=1, kind="stable"), axis=1)


class Forest:
    def __init__(self):
        self.up: dict[int, int] = {}

    def find(self, x: int) -> int:
        while (p := self.up.get(x, x)) != x:
            self.up[x] = x = self.up.get(p, p)
        return x

    def join(self, x: int, y: int) -> None:
        a, b = self.find(x), self.find(y)
        if a != b:
            self.up[max(a, b)] = min(a, b)


def candidate_tiles(tops: np.ndarray, left: np.ndarray, right: np.ndarray, one: int, two: int, shared: float):
    """(a, b, hit): tiles of a list's rows, and which pairs are candidates whose two least common pivots are ``one`` and ``two``.

    ``left`` and ``right`` are the same rows, which gives every pair once and none with itself, or two blocks.
    """
    near, local = np.unique(tops, return_inverse=True)
    local = local.reshape(tops.shape)
    k = tops.shape[1]
    weight = np.zeros((len(tops), len(near)), dtype=np.float32)
    weight[np.arange(len(tops))[:, None], local] = np.arange(k, 0, -1)
    earlier = ((weight > 0) & (near < two) & (near != one)).astype(np.float32)
    least = shared * (np.arange(1, k + 1) ** 2).sum()
    for i in range(0, len(left), TILE):
        a = left[i : i + TILE]
        for j in range(i if left is right else 0, len(right), TILE):
            b = right[j : j + TILE]
            hit = (weight[a] @ weight[b].T >= least) & (earlier[a] @ earlier[b].T == 0)
            if left is right and i == j:
                hit = np.triu(hit, 1)
            if hit.any():
                yield a, b, hit


def _lists(table: pa.Table):
    """(rows, left, right, one, two) of each list and pair of blocks in a bucket; positions in left and right are among ``rows``."""
    lists = table.column("list").to_numpy()
    blocks = np.stack([table.column(c).to_numpy() for c in ("own", "first", "second")], axis=1)
    order = np.lexsort((table.column("rep").to_numpy(), blocks[:, 2], blocks[:, 1], lists))
    key = np.c_[lists, blocks[:, 1:]][order]
    edges = np.r_[0, np.flatnonzero((key[1:] != key[:-1]).any(axis=1)) + 1, len(order)]
    for x, y in zip(edges, edges[1:], strict=False):
        rows = order[x:y]
        if len(rows) > 1:
            first, second = blocks[rows[0], 1:]
            local = np.arange(len(rows))
            left = local if first == second else local[blocks[rows, 0] == first]
            yield rows, left, left if first == second else local[blocks[rows, 0] == second], *divmod(int(lists[rows[0]]), 1 << 32)


def _permutations_of(table: pa.Table) -> np.ndarray:
    return np.frombuffer(b"".join(table.column("tops").to_pylist()), dtype=np.int32).reshape(len(table), -1)


def _retrieve(table: pa.Table, shared: float) -> pa.Table:
    """The postings of a bucket that have a candidate in their list."""
    tops, found = _permutations_of(table), np.zeros(len(table), dtype=bool)
    for rows, left, right, one, two in _lists(table):
        for a, b, hit in candidate_tiles(tops[rows], left, right, one, two, shared):
            found[rows[a[hit.any(axis=1)]]] = True
            found[rows[b[hit.any(axis=0)]]] = True
    return table.filter(pa.array(found))


def _verify(table: pa.Table, dim: int, link: float, shared: float) -> pa.Table:
    """Links of a bucket's candidates: a sum a vector, and a forest."""
    ids, copies = table.column("rep").to_numpy(), table.column("copies").to_numpy().astype(float)
    tops, vectors = _permutations_of(table), units(table.column("embedding").to_pylist(), dim)
    sums, forest = np.zeros(len(ids)), Forest()
    for rows, left, right, one, two in _lists(table):
        own = vectors[rows]
        for a, b, hit in candidate_tiles(tops[rows], left, right, one, two, shared):
            hit &= own[a] @ own[b].T >= link
            if hit.any():
                np.add.at(sums, rows[a], hit @ copies[rows[b]])
                np.add.at(sums, rows[b], copies[rows[a]] @ hit)
                for i in np.flatnonzero(hit.any(axis=1)).tolist():
                    x = int(ids[rows[a[i]]])
                    for y in ids[rows[b[hit[i]]]].tolist():
                        forest.join(x, y)
    who, inverse = np.unique(ids, return_inverse=True)
    total = np.bincount(inverse, weights=sums, minlength=len(who)).astype(np.int64)
    root = [forest.find(int(w)) for w in who]
    keep = [i for i in range(len(who)) if total[i] or root[i] != who[i]]
    return pa.table([pa.array(who[keep], pa.int64()), pa.array(total[keep], pa.int64()), pa.array([root[i] for i in keep], pa.int64())], names=["rep", "links", "root"])


def indexed(groups: DataFrame, dim: int, pivots: np.ndarray, nearest: int) -> DataFrame:
    """(rep, tops, lists) of classes of vectors: the permutation, packed, and the names of the lists that hold the class."""

    @lean
    def run(batches):
        for batch in batches:
            if not len(batch):
                continue
            tops = permutations(units(batch.column("embedding").to_pylist(), dim), pivots, nearest)
            low = np.sort(tops, axis=1).astype(np.int64)
            if low.shape[1] > 1:
                keys = np.stack([low[:, a] << 32 | low[:, b] for a, b in combinations(range(low.shape[1]), 2)], axis=1)
            else:
                keys = low << 32 | 0xFFFFFFFF
            yield pa.RecordBatch.from_arrays([batch.column("rep"), pa.array([t.tobytes() for t in tops.astype(np.int32)], pa.binary()), pa.array(list(keys), pa.list_(pa.int64()))], ["rep", "tops", "lists"])

    return groups.select("rep", "embedding").mapInArrow(run, "rep long, tops binary, lists array<long>")


def near_duplicates(vectors: DataFrame, link: float = LINK, pivot_count: int | None = None, nearest: int = NEAREST, shared: float = SHARED) -> DataFrame:
    """vec_id, n_links, component_id, kept for each row of ``vectors`` (vec_id, embedding)."""
    spark = vectors.sparkSession
    given = vectors.schema["embedding"].dataType.simpleString()
    rows = vectors.select("vec_id", F.col("embedding").cast("array<float>" if given == "array<float>" else "array<double>").alias("embedding"))
    finite = F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("embedding", lambda x: x != 0)
    valid = F.coalesce(finite, F.lit(False)) & F.col("vec_id").isNotNull()
    rows = rows.withColumn("digest", F.when(valid, F.unhex(F.md5(F.to_json(F.struct(F.col("embedding").cast("array<double>").alias("embedding"))).cast("binary")))))
    groups = rows.where("digest is not null").groupBy("digest").agg(F.min("vec_id").alias("rep"), F.count(F.lit(1)).alias("copies"), F.first("embedding").alias("embedding"))
    groups = storage.spill(groups, "vectors")
    dim, n = groups.agg(F.max(F.size("embedding")), F.count(F.lit(1))).first()
    dim, most = dim or 1, pivot_count or max(PIVOTS, int(PIVOTS_PER_ROOT * n**0.5))
    sample = [r.embedding for r in groups.orderBy(F.xxhash64("rep"), "digest").limit(SAMPLED * most).select("embedding").collect()]
    pivots = choose_pivots(units(sample, dim), most) if sample else np.zeros((1, dim))

    entries = storage.spill(indexed(groups, dim, pivots, nearest), "permutations")
    posted = entries.select("rep", "tops", F.explode("lists").alias("list"))
    sizes = storage.spill(posted.groupBy("list").agg(F.count(F.lit(1)).alias("size")).where("size > 1"), "lists")
    blocks = F.ceil(F.col("size") / F.lit(BLOCK)).cast("int")
    dealt = posted.join(storage.small(sizes.select("list", blocks.alias("blocks"))), "list").withColumn("own", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int"))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).withColumn("first", F.least("own", "other")).withColumn("second", F.greatest("own", "other"))
    work = sizes.agg(F.sum(F.col("size") * blocks)).first()[0] or 0
    bucket = lambda entries: F.pmod(F.xxhash64("list", "first", "second"), F.lit(max(4 * storage.width(spark), -(-entries // BUCKET))))

    def retrieve(table: pa.Table) -> pa.Table:
        return _retrieve(table, shared)

    def verify(table: pa.Table) -> pa.Table:
        out = _verify(table, dim, link, shared)
        give_back()
        return out

    postings = dealt.select(bucket(work).alias("bucket"), "list", "own", "first", "second", "rep", "tops")
    met = storage.spill(postings.groupBy("bucket").applyInArrow(retrieve, postings.schema).drop("bucket"), "candidates")
    asked = met.join(groups.select("rep", "copies", "embedding"), "rep").withColumn("bucket", bucket(20 * met.count()))
    linked = storage.spill(asked.groupBy("bucket").applyInArrow(verify, "rep long, links long, root long"), "links")
    storage.release(entries, sizes, met)
    counts = linked.groupBy("rep").agg(F.sum("links").alias("links"))
    members = rows.join(groups.select("digest", "rep", "copies"), "digest", "left")
    # Rows that share an id but not a vector tie their classes.
    tied = members.where("rep is not null and vec_id <> rep").select(F.col("vec_id").alias("a"), F.col("rep").alias("b"))
    label = connected(linked.where("rep <> root").select(F.col("rep").alias("a"), F.col("root").alias("b")).unionByName(tied))
    out = members.join(counts, "rep", "left").join(label, members["vec_id"] == label["node"], "left")
    component = F.coalesce("component", "vec_id")
    n_links = F.when(F.col("copies").isNull(), F.lit(0)).otherwise(F.coalesce("links", F.lit(0)) + F.col("copies") - 1).cast("long")
    return out.select("vec_id", n_links.alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, F.lit(True)).alias("kept"))


def recall_against_brute_force(vectors: DataFrame, every: int = 50, link: float = LINK) -> float:
    """Share of the true links of the rows whose id ``every`` divides that n_links counts; the queries go to all rows in blocks.

    Rows without a valid vector are left out on both sides.
    """
    found = near_duplicates(vectors, link).where(F.col("vec_id") % every == 0).agg(F.sum("n_links")).first()[0] or 0
    valid = lambda v: bool(v) and all(x is not None and np.isfinite(x) for x in v) and any(v)
    queries = [r.embedding for r in vectors.where(F.col("vec_id") % every == 0).select("embedding").collect() if valid(r.embedding)]
    if not queries:
        return 1.0
    dim = vectors.agg(F.max(F.size("embedding"))).first()[0]
    queries = units(queries, dim)

    def count(batches):
        for batch in batches:
            rows = [v for v in batch.column("embedding").to_pylist() if valid(v)]
            n = int((units(rows, dim) @ queries.T >= link).sum()) if rows else 0
            yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64())], ["n"])

    total = vectors.where("vec_id is not null").select("embedding").mapInArrow(count, "n long").agg(F.sum("n")).first()[0] - len(queries)
    return found / total if total else 1.0


def op7_pivots(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(storage.table(spark, sf_dir, "embeddings").select("vec_id", "embedding"))


ORACLE = r"""
WITH RECURSIVE v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings),
l AS (SELECT a.vec_id AS x, b.vec_id AS y FROM v a JOIN v b ON a.vec_id <> b.vec_id AND list_cosine_similarity(a.e, b.e) >= 0.95),
r AS (SELECT vec_id, vec_id AS c FROM v UNION SELECT l.y, r.c FROM r JOIN l ON l.x = r.vec_id WHERE r.c < l.y),
m AS (SELECT vec_id, min(c) AS c FROM r GROUP BY 1)
SELECT vec_id, (SELECT count(*) FROM l WHERE l.x = m.vec_id) AS n_links, c AS component_id, vec_id = c AS kept FROM m
"""
