"""Secret scans with a trigram inverted index; DataFrame functions only.

1. ``trigram_query`` derives from a rule's regex, on the driver, which trigrams any match must hold: a union of
   conjunctions, over text in lower case.  A rule with an alternative that has none scans every text.
2. ``build_index`` writes postings (trigram, doc_id), a sorted segment a task: of all trigrams, for an index that serves any rules, or of
   chosen ones, for a single scan.
3. ``candidates`` intersects the postings of each conjunction: a document stands in all of its lists if it is met as often
   as the conjunction has trigrams.  Any number of rules and trigrams will do.
4. ``scan`` verifies candidates with the regex; the others are not touched by it.

Postings are by doc_id, so rows that share an id, or have none, are candidates together; verification is by row, so every row gets
its own spans.  Null texts are empty.  Extra columns stay where ``scan`` is asked to keep them.  Long texts are indexed in stretches and
verified whole; spans are gathered in runs, so their number costs no squares.  An empty table gives an empty result.
"""

from __future__ import annotations

import re._constants as tok
import re._parser as parser
from dataclasses import dataclass
from itertools import product

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import storage

#: Trigrams of a conjunction that are looked up, at most; alternatives and characters of a class that are spelled out.
LOOKUPS, MOST_ALTERNATIVES, MOST_CHARACTERS = 4, 64, 4


@dataclass(frozen=True)
class Rule:
    """A kind of secret: matches are leftmost and do not overlap; those whose group ``size_of`` is shorter than ``least`` are dropped."""

    kind: str
    regex: str
    least: int = 0
    size_of: int = 0


def either_case(word: str) -> str:
    return "".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in word)


#: The first three are the base kinds; the others add spans.
RULES = (
    Rule("assign", "(?:" + "|".join(map(either_case, ("password", "passwd", "secret", "token", "api_?key"))) + r")[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", 12, 1),
    Rule("access", "AKIA[A-Z0-9]{14,}"),
    Rule("hex", "[0-9a-f]{16,}"),
    Rule("private_key", "-----BEGIN (?:[A-Z]+ )*PRIVATE KEY-----"),
    Rule("github", "gh[pousr]_[A-Za-z0-9]{20,}"),
    Rule("slack", "xox[abprs]-[A-Za-z0-9-]{10,}"),
    Rule("google", "AIza[A-Za-z0-9_-]{30,}"),
    Rule("stripe", "[rs]k_live_[A-Za-z0-9]{16,}"),
    Rule("jwt", r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]+"),
)
BASE = 3


# ---------------------------------------------------------------- trigram queries

GAP = "\x00"


def _alternatives(items) -> set[str]:
    """Strings of what a parsed regex matches, folded; GAP stands for anything."""
    out = {""}
    for op, arg in items:
        if op is tok.LITERAL:
            part = {chr(arg).lower()}
        elif op is tok.IN:
            spelled = set()
            for kind, value in arg:
                if kind is tok.LITERAL:
                    spelled.add(chr(value).lower())
                elif kind is tok.RANGE and value[1] - value[0] < MOST_CHARACTERS:
                    spelled |= {chr(c).lower() for c in range(value[0], value[1] + 1)}
                else:
                    spelled.add(GAP)
            part = {GAP} if GAP in spelled or len(spelled) > MOST_CHARACTERS else spelled
        elif op is tok.SUBPATTERN:
            part = _alternatives(arg[3])
        elif op is tok.BRANCH:
            part = set().union(*(_alternatives(x) for x in arg[1]))
        elif op in (tok.MAX_REPEAT, tok.MIN_REPEAT):
            least, most, inner = arg
            one = _alternatives(inner)
            part = {"".join(x) for x in product(one, repeat=min(least, 3))} if len(one) ** min(least, 3) <= MOST_ALTERNATIVES else {GAP}
            if (least, most) == (0, 1):
                part |= one
            elif most > min(least, 3):
                part = {x + GAP for x in part}
        elif op is tok.AT:
            part = {""}
        else:
            part = {GAP}
        if len(out) * len(part) > MOST_ALTERNATIVES:
            part = {GAP}
        out = {a + b for a in out for b in part}
    return out


def trigram_query(regex: str) -> list[frozenset[str]] | None:
    """A match holds all trigrams of one of these sets; None if some match need not hold any."""
    found = set()
    for text in _alternatives(parser.parse(regex)):
        grams = list(dict.fromkeys(run[i : i + 3] for run in text.split(GAP) for i in range(len(run) - 2)))
        if not grams:
            return None
        step = max(1, (len(grams) - 1) // (LOOKUPS - 1)) if len(grams) > LOOKUPS else 1
        found.add(frozenset(grams[::step][:LOOKUPS]))
    return sorted((s for s in found if not any(o < s for o in found)), key=sorted)


# ---------------------------------------------------------------- index

def asked_trigrams(rules=RULES) -> list[str]:
    return sorted({g for r in rules for conjunction in trigram_query(r.regex) or [] for g in conjunction})


#: Characters of a long text whose trigrams are listed at once.
STRETCH = 1 << 16


def build_index(docs: DataFrame, grams: list[str] | None = None) -> DataFrame:
    """Postings (trigram, doc_id), those of one text once each; of ``grams`` only, if given.  Each task writes a segment sorted by trigram."""
    low = docs.select("doc_id", F.lower(F.col("text")).alias("low"))
    if grams is None:
        # Stretches overlap by two characters; a lookahead lists every trigram in one pass.
        parts = low.select("doc_id", F.monotonically_increasing_id().alias("row"), F.explode(F.regexp_extract_all("low", F.lit(f"(?s)(?=(.{{1,{STRETCH + 2}}})).{{1,{STRETCH}}}"), F.lit(1))).alias("part"))
        found = parts.select("doc_id", F.explode(F.array_distinct(F.regexp_extract_all("part", F.lit("(?s)(?=(...))"), F.lit(1)))).alias("trigram"))
    else:
        held = F.array_compact(F.array(*[F.when(F.contains("low", F.lit(g)), F.lit(g)) for g in grams]))
        found = low.select("doc_id", F.explode(held).alias("trigram"))
    return storage.spill(found.select("trigram", "doc_id").sortWithinPartitions("trigram", "doc_id"), "trigrams")


def candidates(index: DataFrame, rules=RULES) -> DataFrame:
    """(doc_id, rules): the rules of which some conjunction's postings all hold the document."""
    wanted = []
    for r, rule in enumerate(rules):
        for c, conjunction in enumerate(trigram_query(rule.regex) or []):
            wanted += [(gram, r, c, len(conjunction)) for gram in sorted(conjunction)]
    # One row for each trigram of each rule's query: its size depends on the rules alone.
    lists = F.broadcast(index.sparkSession.createDataFrame(wanted, "trigram string, rule int, conjunction int, need int"))
    met = index.join(lists, "trigram").groupBy("doc_id", "rule", "conjunction", "need").agg(F.size(F.collect_set("trigram")).alias("held"))
    return met.where("held = need").groupBy("doc_id").agg(F.collect_set("rule").alias("rules"))


# ---------------------------------------------------------------- verification

#: Spans of one rule, and how many are gathered before they are set aside.
SPANS, RUN = "array<struct<start:int,rule:int,end:int>>", 256


def _java(regex: str) -> str:
    return regex.replace('\\"', '"')


def rule_spans(text: Column, r: int, rule: Rule) -> Column:
    """array<struct<start, rule, end>> of a rule's matches, in code points.

    Each match is taken together with the text since the last one; sums of the lengths give the places.  The anchor keeps
    the engine from trying anew at each later character once there is no further match.
    """
    whole = r"\G(?s)(.*?)(" + _java(rule.regex) + ")"
    gap, hit = (F.regexp_extract_all(text, F.lit(whole), F.lit(g)) for g in (1, 2))
    size = F.regexp_extract_all(text, F.lit(whole), F.lit(2 + rule.size_of)) if rule.size_of else hit
    found = F.arrays_zip(gap.alias("gap"), hit.alias("hit"), size.alias("size"))
    kind = f"struct<at:int,full:array<{SPANS}>,spans:{SPANS}>"
    none = F.array().cast(SPANS)
    start = F.struct(F.lit(0).alias("at"), F.array().cast(f"array<{SPANS}>").alias("full"), none.alias("spans")).cast(kind)

    def add(state, m):
        begin = state["at"] + F.length(m["gap"])
        end = begin + F.length(m["hit"])
        span = F.array(F.struct(begin.alias("start"), F.lit(r).alias("rule"), end.alias("end")))
        long = F.size(state["spans"]) >= RUN
        full = F.when(long, F.concat(state["full"], F.array(state["spans"]))).otherwise(state["full"])
        spans = F.when(long, none).otherwise(state["spans"])
        return F.struct(end.alias("at"), full.alias("full"), F.when(F.length(m["size"]) >= rule.least, F.concat(spans, span)).otherwise(spans).alias("spans")).cast(kind)

    return F.aggregate(found, start, add, lambda s: F.concat(F.flatten(s["full"]), s["spans"]))


def scan(docs: DataFrame, rules=RULES) -> DataFrame:
    """All columns of ``docs`` and secret_spans: array<struct<start, rule, end>>, sorted."""
    index = build_index(docs, asked_trigrams(rules))
    hits = storage.small(storage.spill(candidates(index, rules), "hits").withColumnRenamed("doc_id", "_secret_of").withColumnRenamed("rules", "_secret_rules"))
    marked = docs.join(hits, docs["doc_id"].eqNullSafe(hits["_secret_of"]), "left").drop("_secret_of")
    text, none = F.coalesce(F.col("text"), F.lit("")), F.array().cast(SPANS)
    every = []
    for r, rule in enumerate(rules):
        spans = rule_spans(text, r, rule)
        every.append(spans if trigram_query(rule.regex) is None else F.when(F.array_contains("_secret_rules", r), spans).otherwise(none))
    return marked.withColumn("secret_spans", F.array_sort(F.concat(*every))).drop("_secret_rules")


def spelled(spans: Column, rules=RULES) -> Column:
    names = F.array(*[F.lit(r.kind) for r in rules])
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(names, s["rule"]), s["start"].cast("string"), s["end"].cast("string"))), ",")


def redact(docs: DataFrame, rules=RULES) -> DataFrame:
    """``docs`` with each run of overlapping spans replaced by a mark that names its first kind; n_chars follows."""
    found = scan(docs, rules)
    kind = "array<struct<start:int,rule:int,end:int>>"

    def merge(done, s):
        last = F.element_at(done, -1)
        wider = F.array(F.struct(last["start"].alias("start"), last["rule"].alias("rule"), F.greatest(last["end"], s["end"]).alias("end")))
        return F.when((F.size(done) > 0) & (s["start"] < F.try_element_at(done, F.lit(-1))["end"]), F.concat(F.slice(done, 1, F.greatest(F.size(done) - 1, F.lit(0))), wider)).otherwise(F.concat(done, F.array(s))).cast(kind)

    merged = found.withColumn("_secret_runs", F.when(F.size("secret_spans") > 0, F.aggregate("secret_spans", F.array().cast(kind), merge)))
    names = F.array(*[F.lit(f"[{r.kind}]") for r in rules])
    tail = F.transform("_secret_runs", lambda s, i: F.concat(F.get(names, s["rule"]), F.substring(F.col("text"), s["end"] + 1, F.coalesce(F.get(F.col("_secret_runs"), i + 1)["start"], F.length("text")) - s["end"])))
    text = F.when(F.col("_secret_runs").isNull(), F.col("text")).otherwise(F.concat(F.substring(F.col("text"), F.lit(1), F.get(F.col("_secret_runs"), F.lit(0))["start"]), F.array_join(tail, "")))
    return merged.withColumn("text", text).withColumn("n_chars", F.length("text").cast("long")).drop("_secret_runs", "secret_spans")


def of_rule(r: int) -> Column:
    return F.size(F.filter("secret_spans", lambda s: s["rule"] == r))


def op1_secrets(spark, sf_dir: str) -> DataFrame:
    found = scan(storage.table(spark, sf_dir, "documents").select("doc_id", "text"))
    count = [of_rule(r).cast("long").alias(f"n_{RULES[r].kind}") for r in range(BASE)]
    base = F.filter("secret_spans", lambda s: s["rule"] < BASE)
    return found.select("doc_id", *count, F.sha2(spelled(base), 256).alias("base_sha256"), spelled(F.col("secret_spans")).alias("spans"))


def _sql() -> str:
    quoted = [r.regex.replace('\\"', '"').replace("'", "''") for r in RULES]
    parts = []
    for i, (r, q) in enumerate(zip(RULES, quoted, strict=True)):
        whole = f"'(?s)(.*?)({q})'"
        size = f"regexp_extract_all(t, {whole}, {2 + r.size_of})"
        parts.append(f"SELECT k, {i} AS rule, '{r.kind}' AS kind, {r.least} AS least, unnest(regexp_extract_all(t, {whole}, 1)) AS gap, unnest(regexp_extract_all(t, {whole}, 2)) AS hit, unnest({size}) AS size, generate_subscripts(regexp_extract_all(t, {whole}, 2), 1) AS i FROM d")
    return f"""
WITH d AS (SELECT row_number() OVER () AS k, doc_id, coalesce(text, '') AS t FROM documents),
m AS ({' UNION ALL '.join(parts)}),
p AS (SELECT *, sum(length(gap) + length(hit)) OVER (PARTITION BY k, rule ORDER BY i) AS stop FROM m),
s AS (SELECT k, rule, kind, stop - length(hit) AS start, stop FROM p WHERE length(size) >= least),
a AS (SELECT k, count(*) FILTER (rule = 0) AS n_assign, count(*) FILTER (rule = 1) AS n_access, count(*) FILTER (rule = 2) AS n_hex,
  string_agg(kind || ':' || start || ':' || stop, ',' ORDER BY start, rule, stop) FILTER (rule < {BASE}) AS base,
  string_agg(kind || ':' || start || ':' || stop, ',' ORDER BY start, rule, stop) AS spans FROM s GROUP BY k)
SELECT doc_id, coalesce(n_assign, 0) AS n_assign, coalesce(n_access, 0) AS n_access, coalesce(n_hex, 0) AS n_hex,
  sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans FROM d LEFT JOIN a USING (k)
"""


ORACLE = _sql()
