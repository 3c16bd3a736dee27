"""Generated graphs, from ``spark.range`` and arithmetic only: undirected pairs (src, dst, w) with src < dst."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import PRIME, mix, mix_sql
from ..model import canonical


def _links(spark: SparkSession, n: int, *targets) -> DataFrame:
    """Edges from i (0 .. n - 1) to each target, a function of i that gives a Column or null."""
    base = spark.range(n)
    return canonical(base.select(F.col("id").alias("src"), F.explode(F.array_compact(F.array(*[t(F.col("id")) for t in targets]))).alias("dst")), w=None)


def grid(spark: SparkSession, r: int, c: int, wrapped: bool = False) -> DataFrame:
    right = lambda i: F.when(F.lit(wrapped) | (i % c < c - 1), i - i % c + (i % c + 1) % c)
    down = lambda i: F.when(F.lit(wrapped) | (i < (r - 1) * c), (i + c) % (r * c))
    return _links(spark, r * c, right, down)


def torus(spark: SparkSession, r: int, c: int) -> DataFrame:
    return grid(spark, r, c, wrapped=True)


def path(spark: SparkSession, n: int) -> DataFrame:
    return _links(spark, n, lambda i: F.when(i < n - 1, i + 1))


def ring(spark: SparkSession, n: int) -> DataFrame:
    return _links(spark, n, lambda i: (i + 1) % n)


def star(spark: SparkSession, n: int) -> DataFrame:
    return _links(spark, n, lambda i: F.when(i > 0, F.lit(0).cast("long")))


def cliques(spark: SparkSession, b: int, s: int) -> DataFrame:
    base = spark.range(b * s).select(F.col("id").alias("src"))
    return canonical(base.withColumn("dst", F.explode(F.sequence(F.col("src") + 1, F.expr(f"src - src % {s} + {s}")))).where(f"dst div {s} = src div {s}"), w=None)


def planted(spark: SparkSession, n: int = 400, b: int = 8, din: int = 6, dout: int = 1) -> DataFrame:
    """b dense groups; ``din`` links of a node go into its group and ``dout`` anywhere."""
    z = n // b
    inner = [lambda i, j=j: F.expr(f"id div {z} * {z}") + mix(i * din + j, 1) % z for j in range(din)]
    outer = [lambda i, j=j: mix(i * dout + j, 2) % n for j in range(dout)]
    return _links(spark, n, *inner, *outer)


def powerlaw(spark: SparkSession, n: int = 5000, m: int = 40000) -> DataFrame:
    x, y = mix("id", 1) % n, mix("id", 2) % n
    ends = spark.range(m).select(x.alias("x"), y.alias("y"))
    return canonical(ends.select(F.expr(f"x * x * x div {n * n}").alias("src"), F.expr(f"y * y * y div {n * n}").alias("dst")), w=None)


def geometric(spark: SparkSession, n: int = 2000, cells: int = 32) -> DataFrame:
    """Points hashed to a square of side 2^31 - 1, linked within one cell's width; cells join by equality, distance decides."""
    side = PRIME // cells
    p = spark.range(n).select("id", mix("id", 3).alias("x"), mix("id", 4).alias("y")).withColumn("cx", F.expr(f"x div {side}")).withColumn("cy", F.expr(f"y div {side}"))
    near = p.select("id", "x", "y", F.explode(F.array(*[F.struct((F.col("cx") + i).alias("cx"), (F.col("cy") + j).alias("cy")) for i in (-1, 0, 1) for j in (-1, 0, 1)])).alias("c")).select(F.col("id").alias("src"), F.col("x").alias("x2"), F.col("y").alias("y2"), "c.cx", "c.cy")
    met = near.join(p.withColumnRenamed("id", "dst"), ["cx", "cy"]).where("src < dst").where((F.col("x") - F.col("x2")) * (F.col("x") - F.col("x2")) + (F.col("y") - F.col("y2")) * (F.col("y") - F.col("y2")) <= side * side)
    return met.select("src", "dst", F.lit(1).cast("long").alias("w"))


#: Fixtures, and the same as SQL.
FIXTURES = {
    "grid": lambda s: grid(s, 32, 32), "torus": lambda s: torus(s, 16, 16), "planted": planted, "powerlaw": powerlaw, "cliques": lambda s: cliques(s, 8, 10),
    "star": lambda s: star(s, 101), "ring": lambda s: ring(s, 64), "path": lambda s: path(s, 64), "geometric": geometric,
}


def _sql(select: str) -> str:
    return f"SELECT CAST(least(src, dst) AS BIGINT) AS src, CAST(greatest(src, dst) AS BIGINT) AS dst, count(*) AS w FROM ({select}) WHERE src <> dst GROUP BY 1, 2"


SQL = {
    "grid": _sql("SELECT range AS src, range + 1 AS dst FROM range(1024) WHERE range % 32 < 31 UNION ALL SELECT range, range + 32 FROM range(992)"),
    "torus": _sql("SELECT range AS src, range // 16 * 16 + (range + 1) % 16 AS dst FROM range(256) UNION ALL SELECT range, (range + 16) % 256 FROM range(256)"),
    "planted": _sql(f"SELECT i AS src, i // 50 * 50 + {mix_sql('6 * i + j', 1)} % 50 AS dst FROM range(400) a(i), range(6) b(j) UNION ALL SELECT i, {mix_sql('i', 2)} % 400 FROM range(400) a(i)"),
    "powerlaw": _sql(f"SELECT x * x * x // 25000000 AS src, y * y * y // 25000000 AS dst FROM (SELECT {mix_sql('i', 1)} % 5000 AS x, {mix_sql('i', 2)} % 5000 AS y FROM range(40000) a(i))"),
    "cliques": _sql("SELECT a.i AS src, b.i AS dst FROM range(80) a(i), range(80) b(i) WHERE a.i < b.i AND a.i // 10 = b.i // 10"),
    "star": _sql("SELECT 0 AS src, range AS dst FROM range(1, 101)"),
    "ring": _sql("SELECT range AS src, (range + 1) % 64 AS dst FROM range(64)"),
    "path": _sql("SELECT range AS src, range + 1 AS dst FROM range(63)"),
    "geometric": f"""WITH p AS (SELECT i, {mix_sql('i', 3)} AS x, {mix_sql('i', 4)} AS y FROM range(2000) t(i))
        SELECT a.i AS src, b.i AS dst, CAST(1 AS BIGINT) AS w FROM p a JOIN p b ON a.i < b.i WHERE (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) <= {(PRIME // 32) ** 2}""",
}
