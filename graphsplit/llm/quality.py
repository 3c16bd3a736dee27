"""Quality rules: statistics of each text, two fixed rules, and an isolation forest over the statistics.

``rule_statistics`` makes one row a document.  ``IsolationForest.over`` is fitted on every row that passes the two rules, without a sample:
all of them bound each split of each tree and are counted in its leaves.  A text's score comes from the mean depth at which random splits
set it apart.  ``calibrated`` picks, on all labelled rows, the score above which a text is refused: the one with the largest share of bad
rows refused less share of good rows refused.

Null texts have no words and fail the first rule; repeated rows get equal results; null ids are kept.  Without
labelled good rows, or where bad rows score no higher than good ones, the forest refuses nothing; without labelled
bad rows it refuses what lies above all but ``MOST_REFUSED`` of the good.  An empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import storage
from .textkit import BASE_A, lean, slices, window_hash, word_hashes

#: ``TREE_ROWS`` is for forests over arrays in memory; those over tables take every row.
TREES, TREE_ROWS, DEPTH = 100, 256, 9
#: Scores are multiples of one by this, so that labelled rows can be counted by score, all of them.
SCORE_STEPS = 1 << 16
#: Share of the labelled good rows that may be refused if no bad row is labelled.
MOST_REFUSED = 0.002
SYMBOLS, BLANKS, WINDOW = "#*$%&|<>", " \t\n\x0b\x0c\r", 8

STATISTICS = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, n_distinct long, n_digits long, n_lines long"
COUNTED = [x.split()[0] for x in STATISTICS.split(", ")][1:]
FEATURES = 8


def repeated_words(hashes: np.ndarray, length: int = WINDOW) -> int:
    """Words inside windows of ``length`` words that the text holds twice or more, the first of them included."""
    if len(hashes) < length + 1:
        return 0
    _, inverse, count = np.unique(window_hash(hashes, length, BASE_A), return_inverse=True, return_counts=True)
    starts = np.flatnonzero(count[inverse] > 1)
    if not len(starts):
        return 0
    return int(length + np.minimum(np.diff(starts), length).sum())


def rule_statistics(docs: DataFrame) -> DataFrame:
    """Counts a document; nothing is shuffled."""

    def row(text: str | None) -> tuple:
        text = text or ""
        words = text.encode("utf-8", "surrogatepass").split()
        lines = text.split("\n")
        seen, again = set(), 0
        for line in lines:
            if line in seen:
                again += bool(line.strip(BLANKS))
            else:
                seen.add(line)
        hashes = word_hashes(words)
        return (len(words), len(text) - sum(map(text.count, BLANKS)), sum(map(text.count, SYMBOLS)), again, repeated_words(hashes), len(np.unique(hashes)), sum(map(text.count, "0123456789")), len(lines))

    @lean
    def run(batches):
        for ids, texts in slices(batches, ["doc_id", "text"]):
            cols = list(zip(*map(row, texts), strict=True))
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in (ids, *cols)], [x.split()[0] for x in STATISTICS.split(", ")])

    return docs.select("doc_id", "text").mapInArrow(run, STATISTICS)


def features(stats: dict[str, np.ndarray]) -> np.ndarray:
    """Rates that the forest splits on, one row a text."""
    n = np.maximum(stats["n_words"], 1).astype(float)
    chars = np.maximum(stats["word_chars"], 1).astype(float)
    return np.stack([
        np.log1p(stats["n_words"]), chars / n, stats["n_symbols"] / chars, stats["n_dup_lines"] / np.maximum(stats["n_lines"], 1),
        stats["n_repeat_words"] / n, stats["n_distinct"] / n ** 0.8, stats["n_digits"] / chars, np.log1p(n / np.maximum(stats["n_lines"], 1)),
    ], axis=1)


def mean_depth(n: np.ndarray | float) -> np.ndarray:
    """Mean depth of an unsuccessful search in a random binary tree of n rows."""
    n = np.asarray(n, dtype=float)
    safe = np.maximum(n, 2.0)
    return np.where(n <= 1, 0.0, np.where(n <= 2, 1.0, 2 * (np.log(safe - 1) + 0.5772156649) - 2 * (safe - 1) / safe))


class IsolationForest:
    """Random axis-parallel splits; trees are heaps of fixed depth in three arrays."""

    def __init__(self, rows: np.ndarray, trees: int = TREES, tree_rows: int = TREE_ROWS, depth: int = DEPTH, seed: int = 7):
        rng = np.random.default_rng(seed)
        size = (1 << (depth + 1)) - 1
        self.depth = depth
        self.axis = np.full((trees, size), -1, dtype=np.int16)
        self.at = np.zeros((trees, size))
        self.path = np.zeros((trees, size))
        self.rows = min(tree_rows, len(rows))
        for t in range(trees):
            held = {0: rows[rng.choice(len(rows), self.rows, replace=False)]}
            for node in range(size):
                x = held.pop(node, None)
                if x is None:
                    continue
                level = (node + 1).bit_length() - 1
                low, high = x.min(axis=0), x.max(axis=0)
                open_ = np.flatnonzero(high > low)
                if level == depth or len(x) <= 1 or not len(open_):
                    self.path[t, node] = level + mean_depth(len(x))
                    continue
                a = rng.choice(open_)
                cut = rng.uniform(low[a], high[a])
                self.axis[t, node], self.at[t, node] = a, cut
                left = x[:, a] < cut
                held[2 * node + 1], held[2 * node + 2] = x[left], x[~left]
        self.usual = float(max(mean_depth(self.rows), 1e-9))

    @classmethod
    def over(cls, stats: DataFrame, trees: int = TREES, depth: int = DEPTH, seed: int = 7) -> IsolationForest | None:
        """Every tree fitted on every row of a table of statistics; None if it has no rows.

        One pass a level: tasks send the extent and the number of their rows in each node, never rows, and the driver draws the splits of the merged
        nodes, at most 2 ** depth a tree.  Extents and counts do not depend on how rows are dealt, so neither does the forest.
        """
        rng = np.random.default_rng(seed)
        size = (1 << (depth + 1)) - 1
        new = cls.__new__(cls)
        new.depth, new.rows, new.usual = depth, 0, 1.0
        new.axis, new.at, new.path = np.full((trees, size), -1, dtype=np.int16), np.zeros((trees, size)), np.zeros((trees, size))
        for level in range(depth + 1):
            tree, node, n, low, high = _extents(stats, new, level)
            if level == 0:
                if not len(n):
                    return None
                new.rows = int(n[0])
                new.usual = float(max(mean_depth(new.rows), 1e-9))
            new.path[tree, node] = level + mean_depth(n)
            split = np.flatnonzero((n > 1) & (high > low).any(axis=1)) if level < depth else []
            if not len(split):
                break
            tree, node, low, high = tree[split], node[split], low[split], high[split]
            a = np.where(high > low, rng.random(low.shape), -1.0).argmax(axis=1)
            every = np.arange(len(a))
            new.axis[tree, node], new.at[tree, node] = a, rng.uniform(low[every, a], high[every, a])
            new.path[tree, 2 * node + 1] = new.path[tree, 2 * node + 2] = level + 1
        return new

    def reached(self, t: int, x: np.ndarray, steps: int) -> np.ndarray:
        """Node of tree ``t`` that each row is in after at most so many splits."""
        every, axis, at = np.arange(len(x)), self.axis[t], self.at[t]
        node = np.zeros(len(x), dtype=np.int64)
        for _ in range(steps):
            a = axis[node]
            inner = a >= 0
            if not inner.any():
                break
            right = x[every, np.maximum(a, 0)] >= at[node]
            node = np.where(inner, 2 * node + 1 + right, node)
        return node

    def score(self, x: np.ndarray) -> np.ndarray:
        """Near 1: set apart early; near 0.5 and below: usual."""
        total = np.zeros(len(x))
        for t, path in enumerate(self.path):
            total += path[self.reached(t, x, self.depth)]
        return 2.0 ** (-total / len(self.axis) / self.usual)


def _extents(stats: DataFrame, forest: IsolationForest, level: int) -> tuple[np.ndarray, ...]:
    """Of each node at ``level`` of each tree: tree, node, rows in it, least and greatest value of each feature (none at the last level)."""
    first, trees, k = (1 << level) - 1, len(forest.axis), FEATURES if level < forest.depth else 0
    names = ["tree", "node", "n", *[f"low{i}" for i in range(k)], *[f"high{i}" for i in range(k)]]

    def run(batches):
        n = np.zeros((trees, first + 1), dtype=np.int64)
        low, high = np.full((trees, first + 1, k), np.inf), np.full((trees, first + 1, k), -np.inf)
        for batch in batches:
            x = features({c: batch.column(c).to_numpy() for c in COUNTED})
            for t in range(trees):
                place = forest.reached(t, x, level) - first  # below 0: in a leaf higher up
                order = np.argsort(place, kind="stable")
                order = order[np.searchsorted(place[order], 0) :]
                if not len(order):
                    continue
                place = place[order]
                starts = np.flatnonzero(np.r_[True, place[1:] != place[:-1]])
                at = place[starts]
                n[t, at] += np.diff(np.r_[starts, len(place)])
                if k:
                    low[t, at] = np.minimum(low[t, at], np.minimum.reduceat(x[order], starts, axis=0))
                    high[t, at] = np.maximum(high[t, at], np.maximum.reduceat(x[order], starts, axis=0))
        tree, place = np.nonzero(n)
        if len(tree):
            values = [tree, place + first, n[tree, place], *low[tree, place].T, *high[tree, place].T]
            yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(v)) for v in values], names)

    schema = ", ".join(f"{c} {'long' if i < 3 else 'double'}" for i, c in enumerate(names))
    merged = stats.select(*COUNTED).mapInArrow(run, schema).groupBy("tree", "node").agg(F.sum("n").alias("n"), *[(F.min(c) if c.startswith("low") else F.max(c)).alias(c) for c in names[3:]])
    got = merged.toArrow().sort_by([("tree", "ascending"), ("node", "ascending")])
    tree, node, n, *ends = [got.column(c).to_numpy() for c in names]
    table = np.array(ends).reshape(2, k, len(n))
    return tree, node, n, table[0].T, table[1].T


def calibrated(good: np.ndarray, bad: np.ndarray, most_refused: float = MOST_REFUSED, good_rows: np.ndarray | None = None, bad_rows: np.ndarray | None = None) -> float:
    """Score above which a text is refused: half-way between the two labelled scores where balanced accuracy is best, the higher of equals.

    ``good_rows`` and ``bad_rows`` tell how many rows have each score; one if they are left out.
    """
    if not len(good):
        return np.inf
    at = np.unique(np.concatenate([good, bad]))

    def above(scores: np.ndarray, rows: np.ndarray | None) -> tuple[np.ndarray, int]:
        count = np.zeros(len(at), dtype=np.int64)
        np.add.at(count, np.searchsorted(at, scores), 1 if rows is None else rows)
        return count.sum() - np.cumsum(count), int(count.sum())

    (refused, n_good), (caught, n_bad) = above(good, good_rows), above(bad, bad_rows)
    if not n_bad:
        return float(at[np.argmax(refused <= most_refused * n_good)]) + 1e-6
    best = len(at) - 1 - int(np.argmax((caught * n_good - refused * n_bad)[::-1]))
    return float(at[best] + at[best + 1]) / 2 if best + 1 < len(at) else np.inf


def judge(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Statistics of each document with base_failed, anomaly (the forest's score) and kept.

    The statistics table is written once; the forest is fitted on all rows of it that pass the rules, and all labelled ones of these are counted by
    score, at most ``SCORE_STEPS`` + 1 rows of either kind in the driver.
    """
    base = (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))
    stats = storage.spill(rule_statistics(docs).withColumn("base_failed", base), "statistics")
    forest = IsolationForest.over(stats.where(~F.col("base_failed")))

    def run(batches):
        for batch in batches:
            score = np.round(forest.score(features({c: batch.column(c).to_numpy() for c in COUNTED})) * SCORE_STEPS) / SCORE_STEPS if forest else np.zeros(len(batch))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(score)], [*batch.schema.names, "anomaly"])

    scored = storage.spill(stats.mapInArrow(run, STATISTICS + ", base_failed boolean, anomaly double"), "scored")
    storage.release(stats)
    marked = scored.where(~F.col("base_failed")).select("doc_id", "anomaly").join(labels.select("doc_id", "quality").where("quality in (0, 1)").distinct(), "doc_id")
    counts = marked.groupBy("quality", "anomaly").agg(F.count(F.lit(1)).alias("rows")).toArrow().to_pandas()
    good, bad = (counts[counts.quality == q] for q in (1, 0))
    refuse_above = calibrated(good.anomaly.to_numpy(), bad.anomaly.to_numpy(), MOST_REFUSED, good["rows"].to_numpy(), bad["rows"].to_numpy())
    return scored.withColumn("kept", ~F.col("base_failed") & (F.col("anomaly") <= F.lit(refuse_above)))


def op8_quality(spark, sf_dir: str) -> DataFrame:
    judged = judge(storage.table(spark, sf_dir, "documents"), storage.table(spark, sf_dir, "labels"))
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "anomaly")
