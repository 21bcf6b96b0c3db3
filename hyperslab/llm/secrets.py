"""Secret scans over a trigram inverted index, in DataFrame functions only.

From each rule's pattern follows a Boolean query on trigrams that every match must contain: alternatives of sets.
The index holds, per trigram that some query mentions, the documents it occurs in (its postings). Intersecting
and uniting postings gives each rule's candidates, and the patterns run over those. A rule without mandatory
trigrams runs over every text.

Cases: a null text is empty; a null or repeated id is looked up like any other, and the rows of one id are
candidates together but matched each by itself; ties in spans are listed in the order of the rules; an empty
table gives an empty result; further columns are ignored; texts of any length are read whole.
"""

from __future__ import annotations

import re
from dataclasses import dataclass
from itertools import product

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common

# `re` keeps its parser in a module of its own.
from re import _constants as _c  # isort: skip
from re import _parser


@dataclass(frozen=True)
class Rule:
    """Leftmost non-overlapping matches of pattern; those of fewer than least characters (in group, 0 for all) drop."""

    kind: str
    pattern: str
    least: int = 0
    group: int = 0


#: The base rules, then those the scan adds.
BASE = (
    Rule("assign", r"(?i:(password|passwd|secret|token|api_?key))[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", 8, 2),
    Rule("access", r"AKIA[A-Z0-9]+", 16),
    Rule("hex", r"[0-9a-f]+", 32),
)
MORE = (
    Rule("temporary", r"ASIA[A-Z0-9]{16}"),
    Rule("private_key", r"-----BEGIN (?:[A-Z]+ )?PRIVATE KEY-----"),
    Rule("code_host", r"gh[pousr]_[A-Za-z0-9]{36}"),
    Rule("chat_bot", r"xox[abprs]-[A-Za-z0-9-]{10,}"),
    Rule("web_key", r"AIza[0-9A-Za-z_-]{35}"),
    Rule("signed_json", r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}"),
)

#: Alternatives that a query may have before it is given up as always true.
_MOST = 64


def trigram_query(pattern: str) -> list[frozenset[str]] | None:
    """Sets of lower-case trigrams, of which a match has all of one set at least; None if nothing is mandatory.

    Walks the parsed pattern with, for each node, the exact strings it stands for while these are few. Where a
    part isn't exact, the strings so far give up their trigrams and a new run begins.
    """
    exact, sets = _strings(_parser.parse(pattern))
    found = [frozenset(s | _trigrams(x)) for x, s in product(exact if exact is not None else [""], sets)]
    return None if any(not s for s in found) else sorted(set(found), key=sorted)


def _trigrams(x: str) -> frozenset[str]:
    return frozenset(x[k : k + 3] for k in range(len(x) - 2))


def _strings(nodes) -> tuple[list[str] | None, list[frozenset[str]]]:
    """(the strings that nodes stand for, None if not just these; alternatives of trigram sets already certain)."""
    run: list[str] = [""]
    certain: list[frozenset[str]] = [frozenset()]
    broken = False

    def close() -> None:
        nonlocal run, certain
        certain = _few([c | _trigrams(x) for c, x in product(certain, run)])
        run = [""]

    for kind, value in nodes:
        strings: list[str] | None = None
        inner: list[frozenset[str]] = [frozenset()]
        if kind is _c.LITERAL:
            strings = [chr(value).lower()]
        elif kind is _c.IN and all(k is _c.LITERAL for k, _ in value):
            strings = sorted({chr(v).lower() for _, v in value})
        elif kind is _c.SUBPATTERN:
            strings, inner = _strings(value[3])
        elif kind is _c.BRANCH:
            each = [_strings(x) for x in value[1]]
            if all(s is not None for s, _ in each):
                strings = sorted({x for s, _ in each for x in s})
            else:
                inner = _few([i | _trigrams(x) for s, more in each for x in (s or [""]) for i in more])
        elif kind in (_c.MAX_REPEAT, _c.MIN_REPEAT):
            low, high, inside = value
            part, more = _strings(inside)
            if part is not None and high == 1:
                strings = sorted({*part, *([""] if low == 0 else [])})
            elif part is not None and low == high and len(part) ** low <= _MOST:
                strings = ["".join(x) for x in product(part, repeat=low)]
            elif low:
                inner = more if part is None else _few([_trigrams(x) for x in part])
        if strings is None:
            close()
            certain, broken = _few([a | b for a, b in product(certain, inner)]), True
        elif len(run) * len(strings) > _MOST:
            close()
            run, broken = (strings if len(strings) <= _MOST else [""]), True
        else:
            run = [a + b for a, b in product(run, strings)]
    if not broken:
        return run, certain
    close()
    return None, certain


def _few(sets: list[frozenset[str]]) -> list[frozenset[str]]:
    """Without alternatives that another one implies; one empty set if there are too many."""
    least = [s for s in set(sets) if not any(o < s for o in sets)]
    return least if len(least) <= _MOST else [frozenset()]


def postings(docs: DataFrame, rules: tuple[Rule, ...], *, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """(trigram, id): the documents that hold each trigram of the rules' queries, in either case. Narrow: no shuffle."""
    wanted = sorted({t for r in rules for s in trigram_query(r.pattern) or [] for t in s})
    folded = F.lower(F.coalesce(F.col(text_column), F.lit("")))
    present = F.array_compact(F.array(*(F.when(F.contains("folded", F.lit(t)), F.lit(t)) for t in wanted))) if wanted else F.array().cast("array<string>")
    return docs.select(F.col(id_column).alias("id"), folded.alias("folded")).select("id", F.explode(present).alias("trigram"))


def candidates(index: DataFrame, rules: tuple[Rule, ...]) -> DataFrame:
    """(id, kinds): per document the rules whose query its postings satisfy; rules without a query aren't listed."""
    queries = {r.kind: trigram_query(r.pattern) for r in rules}
    number = {t: k for k, t in enumerate(sorted({t for q in queries.values() for s in q or [] for t in s}))}
    if not number:
        return index.select("id", F.array().cast("array<string>").alias("kinds")).limit(0)
    words = range(0, len(number), 60)
    masks = {w: F.create_map(*(F.lit(x) for t, k in number.items() if w <= k < w + 60 for x in (t, 1 << (k - w)))).cast("map<string,bigint>") for w in words}
    held = index.groupBy("id").agg(*(F.coalesce(F.bit_or(masks[w][F.col("trigram")]), F.lit(0).cast("long")).alias(f"held{w // 60}") for w in words))

    def holds(trigrams: frozenset[str]) -> Column:
        out = F.lit(True)
        for w in words:
            mask = sum(1 << (number[t] - w) for t in trigrams if w <= number[t] < w + 60)
            if mask:
                out = out & (F.col(f"held{w // 60}").bitwiseAND(F.lit(mask).cast("long")) == F.lit(mask).cast("long"))
        return out

    kinds = [F.when(_any([holds(s) for s in q]), F.lit(kind)) for kind, q in queries.items() if q]
    return held.select("id", F.array_compact(F.array(*kinds)).alias("kinds")).where(F.size("kinds") > 0)


def _any(tests: list[Column]) -> Column:
    out = tests[0]
    for t in tests[1:]:
        out = out | t
    return out


def spans_of(text: Column, rule: Rule, order: int) -> Column:
    """Array of (start, end, order) of the rule's matches, in code points, end exclusive.

    Starts are running sums of gaps and matches. Matches are walked in blocks of about the cube root of their number,
    so appending to arrays stays far from quadratic in a text of very many matches.
    """
    pattern = F.lit(rule.pattern)
    found = F.regexp_extract_all(text, pattern, F.lit(0))
    gaps = F.transform(F.split(text, rule.pattern, -1), lambda x: F.char_length(x))
    kept = F.regexp_extract_all(text, pattern, F.lit(rule.group)) if rule.group else found
    both = F.filter(F.arrays_zip(gaps.alias("gap"), F.transform(found, lambda x: F.char_length(x)).alias("size"), F.transform(kept, lambda x: F.char_length(x)).alias("own")), lambda x: x["size"].isNotNull())
    advance = lambda x: x["gap"] + x["size"]
    sums = "struct<at:int,out:array<int>>"
    spans = "struct<at:int,out:array<struct<start:int,end:int,k:int,own:int>>>"

    def walked(matches: Column) -> Column:
        size = F.greatest(F.lit(1), F.ceil(F.pow(F.size(matches), F.lit(1 / 3)))).cast("int")
        blocks = _with(size, lambda n: F.transform(F.sequence(F.lit(0), F.greatest(F.lit(0), F.ceil(F.size(matches) / n).cast("int") - 1)), lambda k: F.slice(matches, k * n + 1, n)))
        return _with(blocks, of_blocks)

    def of_blocks(blocks: Column) -> Column:
        each = F.transform(blocks, lambda b: F.aggregate(b, F.lit(0), lambda acc, x: acc + advance(x)))
        starts = F.aggregate(each, F.struct(F.lit(0).alias("at"), F.array().cast("array<int>").alias("out")).cast(sums), lambda acc, x: F.struct((acc["at"] + x).alias("at"), F.concat(acc["out"], F.array(acc["at"])).alias("out")), lambda acc: acc["out"])
        return _with(starts, lambda at: F.flatten(F.transform(blocks, lambda b, k: of_block(b, F.get(at, k)))))

    def of_block(block: Column, at: Column) -> Column:
        none = F.array().cast("array<struct<start:int,end:int,k:int,own:int>>")
        put = lambda acc, x: F.struct((acc["at"] + x["gap"]).alias("start"), (acc["at"] + advance(x)).alias("end"), F.lit(order).alias("k"), x["own"].alias("own"))
        return F.aggregate(block, F.struct(at.alias("at"), none.alias("out")).cast(spans), lambda acc, x: F.struct((acc["at"] + advance(x)).alias("at"), F.concat(acc["out"], F.array(put(acc, x))).alias("out")), lambda acc: acc["out"])

    return F.transform(F.filter(_with(both, walked), lambda s: s["own"] >= rule.least), lambda s: F.struct(s["start"], s["end"], s["k"]))


def _with(value: Column, then) -> Column:
    """then(value) with value computed once."""
    return F.element_at(F.transform(F.array(value), then), 1)


#: Candidate rows (an id and a number) that may go to every task, about 50 MB; more are joined by salted ids.
BROADCAST_ROWS = 1_000_000
_SALTS = 16


def scan(docs: DataFrame, rules: tuple[Rule, ...] = BASE + MORE, *, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """doc_id and spans: array of (start, end, kind) by start and order of the rules, for every row of docs.

    The candidates are a written table and counted: while they fit, they go to the texts, which stay where they are;
    beyond, texts and candidates meet by id, salted, so that a hot id is split.
    """
    rows = docs.select(F.col(f"`{id_column}`").alias("id"), F.coalesce(F.col(f"`{text_column}`"), F.lit("")).alias("text"))
    indexed = [r.kind for r in rules if trigram_query(r.pattern)]
    bit = {kind: 1 << k for k, kind in enumerate(indexed)}
    found = candidates(postings(rows, rules, id_column="id", text_column="text"), rules)
    mask = F.aggregate("kinds", F.lit(0).cast("long"), lambda acc, x: acc.bitwiseOR(_any_of(bit, x)))
    known = common.written(found.select(F.col("id").alias("known"), mask.alias("mask")), "candidates")
    few = known.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS
    same = F.col("id").eqNullSafe(F.col("known"))
    if few:
        joined = rows.join(F.broadcast(known), same, "left")
    else:
        salted = known.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(_SALTS - 1))))
        joined = rows.withColumn("own", F.pmod(F.xxhash64("text"), F.lit(_SALTS)).cast("int")).join(salted, same & (F.col("own") == F.col("salt")), "left")
    none = F.array().cast("array<struct<start:int,end:int,k:int>>")
    for k, rule in enumerate(rules):
        verified = F.when(F.regexp_like("text", F.lit(once(rule))), spans_of(F.col("text"), rule, k)).otherwise(none)
        met = F.coalesce(F.col("mask"), F.lit(0)).bitwiseAND(F.lit(bit.get(rule.kind, 0)).cast("long")) != 0
        joined = joined.withColumn(f"found_{k}", F.when(met, verified).otherwise(none) if rule.kind in bit else verified)
    kinds = F.array(*(F.lit(r.kind) for r in rules))
    every = F.concat(*(F.col(f"found_{k}") for k in range(len(rules))))
    ordered = F.array_sort(every, lambda a, b: F.when(a["start"] != b["start"], a["start"] - b["start"]).otherwise(a["k"] - b["k"]))
    return joined.select(F.col("id").alias("doc_id"), F.transform(ordered, lambda s: F.struct(s["start"], s["end"], F.element_at(kinds, s["k"] + 1).alias("kind"))).alias("spans"))


def _any_of(bit: dict[str, int], kind: Column) -> Column:
    out = F.lit(0).cast("long")
    for name, value in bit.items():
        out = F.when(kind == name, F.lit(value).cast("long")).otherwise(out)
    return out


def once(rule: Rule) -> str:
    """A pattern that some match needs: for a run of one set of characters, the least length at once."""
    m = re.fullmatch(r"(\[[^\]]+\])\+", rule.pattern)
    return f"{m[1]}{{{rule.least},}}" if m and rule.least else rule.pattern


def written_spans(spans: Column, kinds: list[str] | None = None) -> Column:
    """kind:start:end of the spans (of those kinds), joined by commas."""
    some = spans if kinds is None else F.filter(spans, lambda s: s["kind"].isin(kinds))
    return F.array_join(F.transform(some, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
