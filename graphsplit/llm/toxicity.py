"""Toxicity: a weighted lexicon, matched by Aho-Corasick after folding, normalised by length, with exception phrases.

``fold`` lowers a text, replaces characters that look like Latin letters and digits that stand for letters, and turns what
else is no letter into blanks.  ``learn`` finds word beginnings that mark the labelled toxic rows, weighs them by log-odds,
finds phrases that excuse them, and fits how the weighted sum and its rate by length give a score from 0 to 1.

Null and empty texts have no hits and get the lowest score.  Repeated rows score alike, null ids are kept.  Without labelled rows of
both kinds the lexicon is empty and every text gets the lowest score.  An empty table gives an empty result.
"""

from __future__ import annotations

import unicodedata
from bisect import bisect_right
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import storage
from .textkit import lean, slices

#: Labelled rows that the lexicon and the scores are fitted on, toxic and other, at most.
TOXIC_ROWS, OTHER_ROWS = 1500, 3500
#: Shortest and longest word beginning; least evidence (log-likelihood ratio) for one.
SHORTEST, LONGEST, EVIDENCE = 4, 12, 14.0
THRESHOLD = 0.3

#: Letters of other scripts that look like Latin ones, and signs written for letters.
LOOKALIKES = dict(zip("авекмнорстухіјѕԁԛԝһҽɡαεικνορτυχϲ", "abekmhopctyxijsdqwhegaeikvoptuxc", strict=True))
SIGNS = dict(zip("0134578@$!|€", "oieastbasiie", strict=True))


class Folding(dict):
    """Translation table of all code points by one rule, each worked out when it is first met: compatibility form, lower case, without
    marks and format characters, look-alikes and signs as letters, anything else that is no letter as a blank."""

    def __missing__(self, cp: int) -> str:
        ch = unicodedata.normalize("NFKC", chr(cp)).lower()
        plain = "".join(x for x in unicodedata.normalize("NFD", ch) if not unicodedata.combining(x) and unicodedata.category(x) != "Cf")
        plain = SIGNS.get(plain, "".join(LOOKALIKES.get(x, x) for x in plain))
        out = self[cp] = plain if plain.isalpha() or plain == "" else " "
        return out


#: At most one entry for each code point.
FOLDING = Folding()


def fold(text: str | None) -> str:
    """Folded words, each after one blank; the start of a word is then a blank in a pattern."""
    words = (text or "").translate(FOLDING).split()
    return " " + " ".join(words) if words else ""


@dataclass
class Lexicon:
    """Weights of word beginnings, phrases that excuse a hit inside them, and the score's coefficients."""

    terms: dict[str, float]
    exceptions: list[str] = field(default_factory=list)
    coefficients: tuple[float, float, float] = (-6.0, 0.0, 0.0)

    def automaton(self):
        import ahocorasick

        found = ahocorasick.Automaton()
        for term, weight in self.terms.items():
            found.add_word(" " + term, (len(term), weight))
        for phrase in self.exceptions:
            found.add_word(" " + phrase, (len(phrase), 0.0))
        found.make_automaton()
        return found

    def hits(self, folded: str, automaton) -> float:
        """Sum of the weights of the longest term at each word, without those inside an exception phrase."""
        best: dict[int, float] = {}
        size: dict[int, int] = {}
        excused: list[tuple[int, int]] = []
        for end, (n, weight) in automaton.iter(folded):
            start = end - n + 1
            if weight == 0.0:
                excused.append((start, end))
            elif n >= size.get(start, 0):
                best[start], size[start] = weight, n
        if not excused:
            return sum(best.values())
        # A hit is excused if a phrase that begins no later ends no earlier: the farthest end of those beginnings tells.
        excused.sort()
        begins, ends = [a for a, _ in excused], np.maximum.accumulate([b for _, b in excused]).tolist()
        return sum(w for s, w in best.items() if (k := bisect_right(begins, s)) == 0 or ends[k - 1] < s + size[s] - 1)

    def inputs(self, texts: list[str | None], automaton=None) -> np.ndarray:
        """The weighted sum, damped, and its rate by length."""
        if not self.terms:
            return np.zeros((len(texts), 2))
        automaton = automaton or self.automaton()
        out = []
        for t in texts:
            folded = fold(t)
            total = self.hits(folded, automaton)
            out.append((np.log1p(total), min(3.0, 20.0 * total / (folded.count(" ") + 20))))
        return np.array(out).reshape(-1, 2)

    def score(self, x: np.ndarray) -> np.ndarray:
        a, b, c = self.coefficients
        return 1 / (1 + np.exp(-(a + b * x[:, 0] + c * x[:, 1])))


def _gain(k1: np.ndarray, n1: float, k0: np.ndarray, n0: float) -> np.ndarray:
    """Log-likelihood ratio of two rates against one, where the first is the higher."""
    rate = (k1 + k0) / (n1 + n0)
    with np.errstate(divide="ignore", invalid="ignore"):
        part = np.where(k1 > 0, k1 * np.log(k1 / (n1 * rate)), 0) + np.where(k0 > 0, k0 * np.log(k0 / (n0 * rate)), 0)
    return np.where(k1 / n1 > k0 / n0, 2 * part, 0)


def find_terms(toxic: list[str], other: list[str]) -> dict[str, float]:
    """Word beginnings whose rate is far higher in toxic texts, without those that a shorter or longer choice explains better."""
    counts = []
    for texts in (toxic, other):
        words: Counter = Counter()
        for t in texts:
            for w, n in Counter(t.split()).items():
                words[w] += min(n, 3)  # a text that repeats one word says little more about it
        begin: Counter = Counter()
        for w, n in words.items():
            for k in range(SHORTEST, min(len(w), LONGEST) + 1):
                begin[w[:k]] += n
        counts.append(begin)
    n1, n0 = (max(1, sum(len(t.split()) for t in texts)) for texts in (toxic, other))
    names = [w for w, n in counts[0].items() if n >= 3]
    k1, k0 = np.array([counts[0][w] for w in names], dtype=float), np.array([counts[1][w] for w in names], dtype=float)
    if not names:
        return {}
    gain, odds = _gain(k1, n1, k0, n0), np.log((k1 + 0.5) / n1) - np.log((k0 + 0.5) / n0)
    out: dict[str, float] = {}
    begun: set[str] = set()
    for i in np.lexsort((-np.array([len(w) for w in names]), -gain)):
        w = names[i]
        if gain[i] < EVIDENCE:
            break
        if odds[i] > 2 and not any(w[:k] in out for k in range(SHORTEST, len(w))) and w not in begun:
            out[w] = float(min(odds[i], 6.0)) / 6.0
            begun.update(w[:k] for k in range(SHORTEST, len(w) + 1))
    return out


def find_exceptions(terms: dict[str, float], toxic: list[str], other: list[str]) -> list[str]:
    """Word pairs around a term that other texts hold three times or more and toxic ones never."""
    def pairs(texts: list[str]) -> Counter:
        found: Counter = Counter()
        for t in texts:
            words = t.split()
            for i, w in enumerate(words):
                if any(w[:k] in terms for k in range(SHORTEST, min(len(w), LONGEST) + 1)):
                    found.update([" ".join(words[i - 1 : i + 1])] * (i > 0) + [" ".join(words[i : i + 2])] * (i + 1 < len(words)))
        return found

    bad = pairs(toxic)
    return sorted(p for p, n in pairs(other).items() if n >= 3 and p not in bad)


def fit_score(x: np.ndarray, y: np.ndarray) -> tuple[float, float, float]:
    """Logistic regression with a small penalty, by Newton steps; the two slopes are kept from falling below zero."""
    z = np.c_[np.ones(len(x)), x]
    w = np.array([-3.0, 1.0, 1.0])
    penalty = np.diag([1e-3, 0.05, 0.05])
    for _ in range(40):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        h = (z * (p * (1 - p))[:, None]).T @ z + penalty
        w = w - np.linalg.solve(h, z.T @ (p - y) + penalty @ w)
        w[1:] = np.maximum(w[1:], 0)
    return tuple(float(v) for v in w)


def learn(texts: list[str | None], toxic: list[int], exceptions: list[str] = ()) -> Lexicon:
    """A lexicon from labelled texts; the score is fitted on halves that the terms were not taken from."""
    folded, y = [fold(t) for t in texts], np.array(toxic, dtype=int)
    if len(set(y.tolist())) < 2:
        return Lexicon({}, list(exceptions))

    def words(rows) -> Lexicon:
        bad, good = [folded[i] for i in rows if y[i]], [folded[i] for i in rows if not y[i]]
        terms = find_terms(bad, good)
        return Lexicon(terms, [*exceptions, *find_exceptions(terms, bad, good)])

    half = np.zeros(len(y), dtype=bool)
    for label in (0, 1):
        half[np.flatnonzero(y == label)[::2]] = True
    x = np.zeros((len(y), 2))
    for side in (half, ~half):
        x[~side] = words(np.flatnonzero(side)).inputs([texts[i] for i in np.flatnonzero(~side)])
    out = words(range(len(y)))
    own = out.inputs(texts)
    out.coefficients = fit_score(np.r_[x, own], np.r_[y, y])
    return out


def train(docs: DataFrame, labels: DataFrame) -> Lexicon:
    """Learn from labelled rows outside the held-out quarter; of either kind a bounded number reaches the driver, chosen by hash of doc_id.

    Of rows that share an id one text is taken.
    """
    marked = labels.where(F.col("toxic").isNotNull() & ~held_out(F.col("doc_id"))).select("doc_id", "toxic")
    rows = []
    for kind, most in ((1, TOXIC_ROWS), (0, OTHER_ROWS)):
        chosen = marked.where(F.col("toxic") == kind).dropDuplicates(["doc_id"]).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
        one = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").groupBy("doc_id", "toxic").agg(F.min_by("text", F.xxhash64("text")).alias("text"))
        rows += one.orderBy("doc_id").select("text", "toxic").collect()
    return learn([r.text for r in rows], [r.toxic for r in rows])


def held_out(doc_id):
    """Null ids count as held out: they carry no label."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(True))


def score_documents(docs: DataFrame, lexicon: Lexicon) -> DataFrame:
    """All columns of ``docs`` and toxic_score, in place of any that has this name; nothing is shuffled."""
    docs = docs.drop("toxic_score")
    out = docs.schema.fieldNames()

    @lean
    def run(batches):
        automaton = lexicon.automaton() if lexicon.terms else None
        for *columns, texts in slices(batches, [*out, "text"], as_lists=("",)):
            x = lexicon.inputs(texts.to_pylist(), automaton)
            yield pa.RecordBatch.from_arrays([*columns, pa.array(lexicon.score(x))], [*out, "toxic_score"])

    return docs.mapInArrow(run, docs.select("*", F.lit(0.0).alias("toxic_score")).schema)


def op10_toxicity(spark, sf_dir: str) -> DataFrame:
    docs = storage.table(spark, sf_dir, "documents").select("doc_id", "text")
    scored = score_documents(docs, train(docs, storage.table(spark, sf_dir, "labels")))
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), F.col("toxic_score").alias("score"), (F.col("toxic_score") >= THRESHOLD).cast("int").alias("predicted"))
