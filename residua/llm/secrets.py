"""Secret scans over a trigram inverted index. DataFrame functions only.

Each rule's regular expression is compiled, on the driver, into a Boolean query over trigrams of the lower-cased text:
an OR of ANDs such that every text with a match holds all trigrams of some AND. Postings (trigram, document) are made
for the trigrams that occur in queries, intersected by document, and only candidates are matched against the rule. A
rule without mandatory trigrams has no query and scans every text. Matches are located by splitting the text at them.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

try:
    from re import _constants as sre
    from re import _parser as parser
except ImportError:  # the module's place before Python 3.11
    import sre_constants as sre
    import sre_parse as parser

#: Alternatives beyond which a query is cut short (a weaker query finds more candidates, never fewer).
MOST_TERMS = 64
SPANS = "array<struct<start:int,place:int,end:int,kind:string>>"
#: Findings of a text walked together.
RUN = 128


@dataclass(frozen=True)
class Rule:
    """``pattern`` finds maximal matches left to right; those whose ``group`` is shorter than ``least`` are dropped afterwards."""

    kind: str
    pattern: str
    group: int = 0
    least: int = 1
    base: bool = False


#: Fixed values of the base rules.
BASE = (
    Rule("assign", r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 8, True),
    Rule("access", r"AKIA[A-Z0-9]+", 0, 16, True),
    Rule("hex", r"[0-9a-f]{32,}", 0, 32, True),  # [0-9a-f]+ of 32 characters or more
)
RULES = BASE + (
    Rule("private_key", r"-----BEGIN [A-Z ]*PRIVATE KEY-----"),
    Rule("host_token", r"gh[pousr]_[A-Za-z0-9]+", 0, 40),
    Rule("signed_token", r"eyJ[A-Za-z0-9_-]+\.eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+"),
)


def trigram_query(pattern: str) -> list[frozenset[str]]:
    """OR of ANDs of trigrams that any match must hold; empty if none is mandatory."""
    texts = _texts(parser.parse(pattern))
    terms = [frozenset(part[i : i + 3] for part in way for i in range(len(part) - 2)) for way in texts]
    terms = reduced(list(dict.fromkeys(terms)))
    return [] if not all(terms) or len(terms) > MOST_TERMS else terms


def _texts(tokens) -> list[tuple[str, ...]]:
    """Ways to match, each as the lower-case literal runs it must hold (a break between runs stands for anything)."""
    ways: list[tuple[str, ...]] = [("",)]
    for op, arg in tokens:
        if op is sre.LITERAL:
            more = [(chr(arg).lower(),)]
        elif op is sre.SUBPATTERN:
            more = _texts(arg[3])
        elif op is sre.BRANCH:
            more = [w for branch in arg[1] for w in _texts(branch)]
        elif op is sre.MAX_REPEAT and arg[:2] == (0, 1):
            more = [("",), *_texts(arg[2])]
        elif op is sre.IN and len(arg) <= 5 and all(o is sre.LITERAL for o, _ in arg):
            more = [(chr(c).lower(),) for _, c in arg]
        else:
            more = [("", "")]
        ways = list(dict.fromkeys((*a[:-1], a[-1] + b[0], *b[1:]) for a in ways for b in more))
        if len(ways) > 16 * MOST_TERMS:
            return [("", "")]
    return ways


def reduced(terms: list[frozenset[str]]) -> list[frozenset[str]]:
    """Without the ANDs that another one implies."""
    return [t for t in terms if not any(o < t for o in terms)]


def postings(docs: DataFrame, rules: tuple[Rule, ...] = RULES, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The inverted index: ``(trigram, doc_id)`` for every trigram of the rules' queries that a text holds."""
    grams = sorted({g for r in rules for t in reduced(trigram_query(r.pattern)) for g in t})
    low = docs.select(F.col(key).alias("doc_id"), F.lower(text).alias("low")).where("low is not null and doc_id is not null")
    held = F.array_compact(F.array(*[F.when(F.col("low").contains(g), F.lit(g)) for g in grams])) if grams else F.array().cast("array<string>")
    return low.select("doc_id", F.explode(held).alias("trigram"))


def candidates(index: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """``(doc_id, kinds)``: postings intersected by document; kinds of the rules whose query the document's trigrams meet."""
    grams = sorted({g for r in rules for t in reduced(trigram_query(r.pattern)) for g in t})
    got = index.groupBy("doc_id").agg(*[F.coalesce(F.bool_or(F.col("trigram") == g), F.lit(False)).alias(f"g{i}") for i, g in enumerate(grams)])
    place = {g: f"g{i}" for i, g in enumerate(grams)}

    def meets(rule: Rule) -> Column:
        out = F.lit(False)
        for term in reduced(trigram_query(rule.pattern)):
            one = F.lit(True)
            for g in sorted(term):
                one = one & F.col(place[g])
            out = out | one
        return out

    asked = [r for r in rules if trigram_query(r.pattern)]
    kinds = F.array_compact(F.array(*[F.when(meets(r), F.lit(r.kind)) for r in asked])) if asked else F.array().cast("array<string>")
    return got.select("doc_id", kinds.alias("kinds")).where(F.size("kinds") > 0)


def _spans(rule: Rule, order: int, text: Column) -> Column:
    """Array of (start, place of the kind, end, kind) of a rule's matches, in code points, end exclusive."""
    pattern = F.lit(rule.pattern)
    hits = F.regexp_extract_all(text, pattern, F.lit(0))
    kept = F.regexp_extract_all(text, pattern, F.lit(rule.group))
    gaps = F.split(text, rule.pattern, -1)
    each = F.zip_with(F.slice(gaps, F.lit(1), F.size(hits)), F.arrays_zip(hits.alias("hit"), kept.alias("kept")), lambda g, h: F.struct(F.length(g).alias("gap"), F.length(h["hit"]).alias("n"), F.length(h["kept"]).alias("m")))
    empty = F.array().cast(SPANS)
    start = lambda acc, x: acc["at"] + x["gap"]
    span = lambda acc, x: F.array(F.struct(start(acc, x).alias("start"), F.lit(order).alias("place"), (start(acc, x) + x["n"]).alias("end"), F.lit(rule.kind).alias("kind")))
    step = lambda acc, x: F.struct((start(acc, x) + x["n"]).alias("at"), F.when(x["m"] >= rule.least, F.concat(acc["found"], span(acc, x))).otherwise(acc["found"]).alias("found"))
    # an array that grows by one copies itself: runs of findings are walked one after the other, then joined
    run = lambda acc, k: F.aggregate(F.slice(each, k * RUN + 1, F.lit(RUN)), F.struct(acc["at"].alias("at"), empty.alias("found")), step)
    runs = F.sequence(F.lit(0), F.floor(F.size(each) / RUN).cast("int"))
    walk = F.aggregate(runs, F.struct(F.lit(0).alias("at"), F.array().cast(f"array<{SPANS}>").alias("found")), lambda acc, k: (lambda more: F.struct(more["at"].alias("at"), F.concat(acc["found"], F.array(more["found"])).alias("found")))(run(acc, k)))
    return F.when(F.regexp_like(text, pattern), F.flatten(walk["found"])).otherwise(empty)


def scan(docs: DataFrame, rules: tuple[Rule, ...] = RULES, index: DataFrame | None = None, key: str = "doc_id", text: str = "text") -> DataFrame:
    """All columns of ``docs`` plus ``found``: array of (start, place, end, kind), sorted by start, then rule order.

    Null texts read as empty and have no finding. Rows of one id (or repeated rows) are each scanned if any of them is
    a candidate; rows with a null id are always scanned. ``index`` may be a stored ``postings`` table; without one it is
    made from ``docs``. The join's side of candidates is broadcast only if adaptive execution finds it small.
    """
    index = postings(docs, rules, key, text) if index is None else index
    named = candidates(index, rules).select(F.col("doc_id").alias("__doc"), F.col("kinds").alias("__kinds"))
    rows = docs.join(named, docs[key] == named["__doc"], "left")
    body = F.coalesce(F.col(text), F.lit(""))
    found = []
    for order, rule in enumerate(rules):
        spans = _spans(rule, order, body)
        if trigram_query(rule.pattern):
            asked = F.col(key).isNull() | F.coalesce(F.array_contains("__kinds", rule.kind), F.lit(False))
            spans = F.when(asked, spans).otherwise(F.array().cast(SPANS))
        found.append(spans)
    return rows.withColumn("found", F.array_sort(F.concat(*found))).drop("__doc", "__kinds")


def joined(found: Column) -> Column:
    """``kind:start:end`` of spans, joined by commas."""
    return F.array_join(F.transform(found, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def report(scanned: DataFrame, rules: tuple[Rule, ...] = RULES, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    count = lambda kind: F.size(F.filter("found", lambda s: s["kind"] == kind)).cast("long")
    base = F.filter("found", lambda s: s["place"].isin([i for i, r in enumerate(rules) if r.base]))
    return scanned.select(*keep, *[count(r.kind).alias(f"n_{r.kind}") for r in rules if r.base], F.sha2(joined(base).cast("binary"), 256).alias("base_sha256"), joined(F.col("found")).alias("spans"))


def redacted(scanned: DataFrame, text: str = "text", by: str = "[secret]") -> DataFrame:
    """The text with every found span replaced; overlapping spans are replaced as one."""
    at = lambda a, b: F.substring(text, a + 1, b - a)
    step = lambda acc, s: F.struct(F.concat(acc["out"], F.when(s["start"] >= acc["at"], F.concat(at(acc["at"], s["start"]), F.lit(by))).otherwise(F.lit(""))).alias("out"), F.greatest(acc["at"], s["end"]).alias("at"))
    walk = F.aggregate("found", F.struct(F.lit("").alias("out"), F.lit(0).alias("at")), step)
    rest = F.concat(walk["out"], F.substring(text, walk["at"] + 1, F.length(text)))
    return scanned.withColumn(text, F.when(F.size("found") > 0, rest).otherwise(F.col(text)))
