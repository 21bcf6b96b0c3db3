"""URL filters: rule lists first, then gradient-boosted trees on lexical features.

The trees learn from the URLs that a rule labels, so the rules carry over to hosts they don't name. Hosts are dealt to
ten folds: the trees are fitted on the URLs of six, both verdicts weighing the same; two choose the threshold of the
score; two stay for `held_out`, which measures the result. The block rate of a host's suffix is a feature; a labelled
URL gets it from the other folds only, so that its own label doesn't speak through it.

Statistics, quantiles, trees and threshold come from all labelled URLs. The suffixes of these are of rules only, so the
statistics are at most ten rows per rule. Trees know of a feature only between which two of its quantiles it lies, so
equal vectors of these codes are counted once. The driver keeps up to most_held such vectors; beyond, tasks sum the
histograms of every level over the written table of them, three passes a tree. Sums are of whole numbers, so both ways grow the same trees.

Cases: a null URL or one without :// has an empty host and path and gets a verdict like any other; a null id is
kept; repeated rows are judged one by one; without labelled URLs, or with labels of one kind in the folds that fit,
the verdict is that kind (allow if there is none); an empty table gives an empty result; further columns are ignored,
whatever they are called; URLs of any length are read whole.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..shared import written


@dataclass(frozen=True)
class Rule:
    verdict: str
    rule: str  # host, then path

    @property
    def host(self) -> str:
        return self.rule.partition("/")[0]

    @property
    def path(self) -> str:
        return "/" + self.rule.partition("/")[2]


#: Fixed values.
RULES = (Rule("block", "com/en/"), Rule("allow", "example.com/en/7"), Rule("allow", "net/de/"), Rule("block", "example.net/de/8"), Rule("block", "org/es/"))


def host_of(url: Column) -> Column:
    after = F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://([^/?#]*)", 1)
    return F.translate(after, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def path_of(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://[^/?#]*([^?#]*)", 1)


def ruled(host: Column, path: Column, rules: tuple[Rule, ...]) -> Column:
    """The longest rule that fits: its host is that host or a domain above it, its path begins the path."""
    out = F.lit(None).cast("string")
    for r in sorted(rules, key=lambda r: len(r.rule)):
        fits = ((host == r.host) | host.endswith("." + r.host)) & path.startswith(r.path)
        out = F.when(fits, F.lit(r.rule)).otherwise(out)
    return out


def entropy(text: Column) -> Column:
    """Bits per character of the counts of its characters: runs of the sorted characters, in one walk."""
    letters = F.array_sort(F.filter(F.split(text, ""), lambda c: c != ""))
    term = lambda run: run * F.log2(F.greatest(run, F.lit(1.0)))
    walked = F.aggregate(
        letters,
        F.struct(F.lit("").alias("c"), F.lit(0.0).alias("run"), F.lit(0.0).alias("sum"), F.lit(0.0).alias("n")),
        lambda acc, c: F.struct(
            c.alias("c"),
            F.when(c == acc["c"], acc["run"] + 1).otherwise(F.lit(1.0)).alias("run"),
            F.when(c == acc["c"], acc["sum"]).otherwise(acc["sum"] + term(acc["run"])).alias("sum"),
            (acc["n"] + 1).alias("n"),
        ),
        lambda acc: F.when(acc["n"] > 0, F.log2(acc["n"]) - (acc["sum"] + term(acc["run"])) / acc["n"]).otherwise(F.lit(0.0)),
    )
    return walked


FEATURES = ("length", "host_length", "path_length", "labels", "depth", "digit_ratio", "hyphens", "host_entropy", "parameters", "longest_segment", "number_length", "first_digit", "https", "fragment", "suffix_rate")
FOLDS, FIT, CHOOSE = 10, 6, 8  # folds below FIT fit the trees, those up to CHOOSE choose the threshold, the others are held out


def features(rows: DataFrame) -> DataFrame:
    """Adds the lexical features to rows (url, host, path) except for the suffix rate, and suffix and fold."""
    url = F.coalesce("url", F.lit(""))
    n = F.char_length(url)
    query = F.regexp_extract(url, r"\?([^#]*)", 1)
    number = F.regexp_extract("path", r"([0-9]+)[^0-9]*$", 1)
    return rows.select(
        "*",
        n.cast("double").alias("length"),
        F.char_length("host").cast("double").alias("host_length"),
        F.char_length("path").cast("double").alias("path_length"),
        F.size(F.split("host", r"\.")).cast("double").alias("labels"),
        F.regexp_count("path", F.lit("/")).cast("double").alias("depth"),
        F.when(n > 0, F.regexp_count(url, F.lit("[0-9]")) / n).otherwise(0.0).alias("digit_ratio"),
        F.regexp_count("host", F.lit("-")).cast("double").alias("hyphens"),
        entropy(F.col("host")).alias("host_entropy"),
        F.when(query == "", 0.0).otherwise(F.size(F.split(query, "&")).cast("double")).alias("parameters"),
        F.array_max(F.transform(F.split("path", "/"), lambda s: F.char_length(s))).cast("double").alias("longest_segment"),
        F.char_length(number).cast("double").alias("number_length"),
        F.when(number == "", -1.0).otherwise(F.substring(number, 1, 1).cast("double")).alias("first_digit"),
        url.startswith("https").cast("double").alias("https"),
        url.contains("#").cast("double").alias("fragment"),
        F.element_at(F.split("host", r"\."), -1).alias("suffix"),
        F.pmod(F.xxhash64("host"), F.lit(FOLDS)).cast("int").alias("fold"),
    )


#: Gradients are summed as whole multiples of 1 / UNIT: no order of rows or tasks makes a difference.
UNIT = 1 << 26
BINS, DEPTH = 32, 3
Split = tuple[int, float]  # feature and threshold


def _walk(x: np.ndarray, splits: Sequence[Split]) -> np.ndarray:
    """The leaf of every row in the complete tree of these inner nodes, breadth first."""
    node = np.zeros(len(x), np.int64)
    for _ in range(len(splits).bit_length()):
        f = np.array([s[0] for s in splits])[node]
        t = np.array([s[1] for s in splits])[node]
        node = 2 * node + 1 + (x[np.arange(len(x)), f] > t)
    return node - len(splits)


def _leaf(splits: Sequence[Split], values: Sequence, k: int = 0) -> Column:
    """The value of the leaf in the same tree, over the feature columns."""
    if k >= len(splits):
        return F.lit(values[k - len(splits)])
    f, t = splits[k]
    return F.when(F.col(FEATURES[f]) > t, _leaf(splits, values, 2 * k + 2)).otherwise(_leaf(splits, values, 2 * k + 1))


@dataclass
class Trees:
    """Boosted regression trees of depth 3 on the logistic loss, as arrays of (feature, threshold) and leaf values."""

    base: float
    splits: list[list[Split]]  # per tree the 7 inner nodes, breadth first
    leaves: list[list[float]]

    def raw(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), self.base)
        for splits, values in zip(self.splits, self.leaves, strict=True):
            out += np.array(values)[_walk(x, splits)]
        return out

    def expression(self) -> Column:
        """The same sum as a Spark expression over the feature columns."""
        total = F.lit(self.base)
        for splits, values in zip(self.splits, self.leaves, strict=True):
            total = total + _leaf(splits, values)
        return total

    def at(self, cuts: Sequence[np.ndarray]) -> Trees:
        """Trees over codes as trees over values: code c and less is up to the c-th cut."""
        value = lambda f, c: float(cuts[f][c]) if c < len(cuts[f]) else float("inf")
        return Trees(self.base, [[(f, value(f, int(c))) for f, c in splits] for splits in self.splits], self.leaves)


#: From the trees so far and the upper levels of the next one, for each node of its next level: sums of gradients and of
#: second derivatives by feature and code, in units.
Sums = Callable[[Trees, list[Split]], tuple[np.ndarray, np.ndarray]]


def _best(G: np.ndarray, H: np.ndarray, cuts: Sequence[np.ndarray], least: float) -> tuple[Split, list[tuple[float, float]]]:
    """The split of most gain of a node, and the sums on its two sides; everything stays left if there is no gain."""
    G, H = np.cumsum(G, axis=1), np.cumsum(H, axis=1)
    all_g, all_h = int(G[0, -1]), int(H[0, -1])
    term = lambda g, h: (g / UNIT) ** 2 / (h / UNIT + least)
    best, split = 1e-9, (0, len(cuts[0]))
    for f, some in enumerate(cuts):
        if not len(some):
            continue
        g, h = G[f, : len(some)], H[f, : len(some)]
        gain = term(g, h) + term(all_g - g, all_h - h) - term(all_g, all_h)
        c = int(gain.argmax())
        if gain[c] > best:
            best, split = float(gain[c]), (f, c)
    left = int(G[split]), int(H[split])
    return split, [left, (all_g - left[0], all_h - left[1])]


def grown(sums: Sums, cuts: Sequence[np.ndarray], base: float, *, trees: int, rate: float = 0.3, least: float = 1.0) -> Trees:
    """Fits by Newton steps on histograms of codes; the trees are over codes."""
    made = Trees(base, [], [])
    for _ in range(trees):
        splits: list[Split] = []
        for _ in range(DEPTH):
            found = [_best(G, H, cuts, least) for G, H in zip(*sums(made, splits), strict=True)]
            splits += [split for split, _ in found]
        made.leaves.append([-rate * (g / UNIT) / (h / UNIT + least) for _, sides in found for g, h in sides])
        made.splits.append(splits)
    return made


def held(x: np.ndarray, y: np.ndarray, weight: np.ndarray, n: np.ndarray) -> Sums:
    """Sums over coded vectors in memory; n: how many rows have each."""
    scores: list[np.ndarray] = []

    def sums(made: Trees, splits: list[Split]) -> tuple[np.ndarray, np.ndarray]:
        if not scores:
            scores.append(np.full(len(x), made.base))
        while len(scores) <= len(made.splits):  # a tree is added once
            scores.append(scores[-1] + np.array(made.leaves[len(scores) - 1])[_walk(x, made.splits[len(scores) - 1])])
        q = 1 / (1 + np.exp(-scores[-1]))
        shape = len(splits) + 1, x.shape[1], BINS + 1
        place = ((_walk(x, splits)[:, None] * shape[1] + np.arange(shape[1])) * shape[2] + x).ravel()
        out = []
        for each in (weight * (q - y), weight * np.maximum(q * (1 - q), 1e-6)):
            total = np.zeros(np.prod(shape), np.int64)
            np.add.at(total, place, np.repeat(np.rint(each * UNIT).astype(np.int64) * n, shape[1]))
            out.append(total.reshape(shape))
        return out[0], out[1]

    return sums


def _coded(table: pa.Table | pa.RecordBatch, weights: tuple[float, float]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """What `held` takes, from rows (the features, y, n); weights of the labels false and true."""
    y = table.column("y").cast(pa.int8()).to_numpy() > 0
    x = np.stack([table.column(f).to_numpy() for f in FEATURES], axis=1).astype(np.int64)
    return x, y.astype(float), np.where(y, weights[1], weights[0]), table.column("n").to_numpy()


def counted(codes: DataFrame, weights: tuple[float, float]) -> Sums:
    """The same sums over a table of coded vectors, a pass each: a task sums its rows, Spark the tasks."""

    def sums(made: Trees, splits: list[Split]) -> tuple[np.ndarray, np.ndarray]:
        shape = 2, len(splits) + 1, len(FEATURES), BINS + 1

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = np.zeros(shape, np.int64)
            for batch in batches:
                total += held(*_coded(batch, weights))(made, splits)
            flat = total.ravel()
            place = np.flatnonzero(flat)
            yield pa.RecordBatch.from_arrays([pa.array(place), pa.array(flat[place])], names=["place", "units"])

        total = np.zeros(np.prod(shape), np.int64)
        for r in codes.mapInArrow(run, "place long, units long").groupBy("place").agg(F.sum("units").alias("units")).collect():
            total[r["place"]] = r["units"]
        return tuple(total.reshape(shape))

    return sums


def _base(p: float) -> float:
    p = min(max(p, 1e-3), 1 - 1e-3)
    return float(np.log(p / (1 - p)))


def boosted(x: np.ndarray, y: np.ndarray, weight: np.ndarray | None = None, *, trees: int = 30, rate: float = 0.3, least: float = 1.0) -> Trees:
    """Trees over the values of rows in memory."""
    weight = np.ones(len(x)) if weight is None else weight
    cuts = [np.unique(np.quantile(c, np.linspace(0, 1, BINS + 1)[1:-1], method="lower")) for c in x.T]
    coded = np.stack([np.searchsorted(c, v, side="left") for c, v in zip(cuts, x.T, strict=True)], axis=1)
    return grown(held(coded, y, weight, np.ones(len(x), np.int64)), cuts, _base(np.average(y, weights=weight)), trees=trees, rate=rate, least=least).at(cuts)


@dataclass
class Filter:
    """trees (or the one verdict there is), the score above which a URL is blocked, and the suffix statistics by fold:
    suffix -> fold -> (labelled, blocked)."""

    trees: Trees | str
    threshold: float
    suffixes: dict[str, dict[int, tuple[int, int]]]


def _blocked(rules: tuple[Rule, ...]) -> Column:
    return F.col("rule").isin([r.rule for r in rules if r.verdict == "block"])


def prepared(pages: DataFrame, rules: tuple[Rule, ...] = RULES, *, id_column: str = "page_id", url_column: str = "url") -> DataFrame:
    """page_id, url, host, path, rule, suffix, fold and the features without the suffix rate."""
    rows = pages.select(F.col(f"`{id_column}`").alias("page_id"), F.col(f"`{url_column}`").alias("url"))
    rows = rows.withColumn("host", host_of(F.col("url"))).withColumn("path", path_of(F.col("url")))
    return features(rows.withColumn("rule", ruled(F.col("host"), F.col("path"), rules)))


def statistics(ready: DataFrame, rules: tuple[Rule, ...] = RULES) -> dict[str, dict[int, tuple[int, int]]]:
    """Labelled and blocked URLs by suffix and fold, over all of them: FOLDS rows per rule at most."""
    found: dict[str, dict[int, tuple[int, int]]] = {}
    for r in ready.where("rule is not null").groupBy("suffix", "fold").agg(F.count("*").alias("n"), F.count(F.when(_blocked(rules), 1)).alias("blocked")).collect():
        found.setdefault(r["suffix"], {})[r["fold"]] = r["n"], r["blocked"]
    return found


def with_rate(ready: DataFrame, suffixes: dict[str, dict[int, tuple[int, int]]]) -> DataFrame:
    """Adds suffix_rate: the blocked share of the suffix, drawn to that of all suffixes; for a labelled URL of the other folds."""

    def share(some: list[tuple[int, int]], prior: float) -> float:
        return (sum(b for _, b in some) + 2 * prior) / (sum(n for n, _ in some) + 2)

    prior = share([v for folds in suffixes.values() for v in folds.values()], 0.5)
    out = F.lit(prior)
    for suffix, folds in suffixes.items():
        own = F.lit(share(list(folds.values()), prior))
        for fold in folds:
            others = share([v for f, v in folds.items() if f != fold], prior)
            own = F.when(F.col("rule").isNotNull() & (F.col("fold") == fold), F.lit(others)).otherwise(own)
        out = F.when(F.col("suffix") == suffix, own).otherwise(out)
    return ready.withColumn("suffix_rate", out)


def quantiles(rows: DataFrame, n: int) -> list[np.ndarray]:
    """Per feature the distinct ones of its BINS - 1 quantiles over all n rows, each a value that occurs. Rows are counted
    by value first, so a task has the distinct values of one feature."""
    each = rows.select(F.posexplode(F.array(*FEATURES)).alias("f", "v")).groupBy("f", "v").agg(F.count("*").alias("n"))
    upto = F.sum("n").over(Window.partitionBy("f").orderBy("v").rowsBetween(Window.unboundedPreceding, 0))
    places = F.array(*(F.lit(k * (n - 1) // BINS).cast("long") for k in range(1, BINS)))
    found = each.select("f", "v", "n", upto.alias("upto")).where(F.exists(places, lambda at: (at >= F.col("upto") - F.col("n")) & (at < F.col("upto"))))
    cuts: list[list[float]] = [[] for _ in FEATURES]
    for r in found.collect():
        cuts[r["f"]].append(r["v"])
    return [np.array(sorted(c)) for c in cuts]


def fitted(ready: DataFrame, rules: tuple[Rule, ...] = RULES, *, most_held: int = 100_000, trees: int = 30) -> Filter:
    """The filter from all labelled URLs of all folds but the held-out ones. most_held: vectors of codes that the driver
    keeps; with more of them the histograms are summed in tasks."""
    suffixes = statistics(ready, rules)
    labels = [(f, n, b) for folds in suffixes.values() for f, (n, b) in folds.items() if f < CHOOSE]
    last = FIT if any(f < FIT for f, _, _ in labels) else CHOOSE  # without labels in the folds that fit, all fit
    n, blocked = (sum(v[k] for v in labels if v[0] < last) for k in (1, 2))
    if blocked in (0, n):
        return Filter("block" if n and blocked else "allow", 0.0, suffixes)
    some = with_rate(ready.where(F.col("rule").isNotNull() & (F.col("fold") < CHOOSE)), suffixes)
    some = written(some.select(*(F.col(f).cast("double") for f in FEATURES), (F.col("fold") < last).alias("fit"), _blocked(rules).alias("y")), "url-labels")
    cuts = quantiles(some.where("fit"), n)
    code = lambda f, c: F.size(F.filter(F.lit(c.tolist()), lambda cut: cut < F.col(f))).cast("tinyint").alias(f)
    codes = some.select(*map(code, FEATURES, cuts), "fit", "y").groupBy(*FEATURES, "fit", "y").agg(F.count("*").alias("n"))
    codes = written(codes, "url-codes")
    weights = 0.5 / (1 - blocked / n), 0.5 / (blocked / n)
    fit = codes.where("fit")
    if fit.count() <= most_held:
        sums = held(*_coded(fit.toArrow(), weights))
    else:
        sums = counted(fit, weights)
    made = grown(sums, cuts, 0.0, trees=trees)  # both verdicts weigh the same
    return Filter(made.at(cuts), _threshold(codes.where("not fit").select(made.expression().alias("score"), "y", "n")), suffixes)


def _threshold(rows: DataFrame) -> float:
    """Where both verdicts are hit best on average, over rows (score, y, n); of equally good places the one nearest to 0,
    which is taken without labels of both kinds. One task passes over the distinct scores in their order."""
    block, allow = F.col("block"), F.col("allow")
    each = rows.groupBy("score").agg(F.sum(F.when(F.col("y"), F.col("n")).otherwise(0)).alias("block"), F.sum(F.when(F.col("y"), 0).otherwise(F.col("n"))).alias("allow"))
    total = each.agg(F.sum("block").alias("block"), F.sum("allow").alias("allow"), F.sum(F.when(F.col("score") <= 0, block)).alias("b"), F.sum(F.when(F.col("score") <= 0, allow)).alias("a")).first()
    if not total["block"] or not total["allow"]:
        return 0.0
    share = lambda b, a: ((total["block"] - b) / total["block"] + a / total["allow"]) / 2
    order = Window.orderBy("score")
    places = each.select(
        ((F.col("score") + F.lead("score").over(order)) / 2).alias("place"),
        share(F.sum(block).over(order.rowsBetween(Window.unboundedPreceding, 0)), F.sum(allow).over(order.rowsBetween(Window.unboundedPreceding, 0))).alias("balanced"),
    ).where("place is not null")
    at_zero = share(total["b"] or 0, total["a"] or 0)
    best = places.agg(F.max("balanced")).first()[0]
    if best is None or at_zero >= best - 1e-12:
        return 0.0
    return places.where(F.col("balanced") >= best - 1e-12).orderBy(F.abs("place"), "place").first()["place"]


def scored(ready: DataFrame, made: Filter) -> DataFrame:
    """Adds score (log odds of block; null if the filter is one verdict) and own, the verdict of the filter."""
    if isinstance(made.trees, str):
        return ready.withColumn("score", F.lit(None).cast("double")).withColumn("own", F.lit(made.trees))
    rows = with_rate(ready, made.suffixes).withColumn("score", made.trees.expression())
    return rows.withColumn("own", F.when(F.col("score") > made.threshold, "block").otherwise("allow"))


def judged(pages: DataFrame, rules: tuple[Rule, ...] = RULES, *, most_held: int = 100_000, trees: int = 30, id_column: str = "page_id", url_column: str = "url") -> DataFrame:
    """page_id, host, path, rule, verdict, score."""
    ready = prepared(pages, rules, id_column=id_column, url_column=url_column)
    of_rule = F.lit(None).cast("string")
    for r in rules:
        of_rule = F.when(F.col("rule") == r.rule, F.lit(r.verdict)).otherwise(of_rule)
    rows = scored(ready, fitted(ready, rules, most_held=most_held, trees=trees))
    return rows.select("page_id", "host", "path", "rule", F.coalesce(of_rule, F.col("own")).alias("verdict"), "score")


def held_out(pages: DataFrame, rules: tuple[Rule, ...] = RULES, **how) -> DataFrame:
    """n, accuracy, majority (the accuracy of always giving the more frequent label), precision and recall of block, over
    the labelled URLs of the hosts that neither fitted the trees nor chose the threshold."""
    ready = prepared(pages, rules)
    rows = scored(ready, fitted(ready, rules, **how)).where(F.col("rule").isNotNull() & (F.col("fold") >= CHOOSE)).select(_blocked(rules).alias("y"), (F.col("own") == "block").alias("p"))
    count = lambda c: F.count(F.when(c, 1))
    y, p = F.col("y"), F.col("p")
    return rows.agg(
        F.count("*").alias("n"),
        F.avg((y == p).cast("double")).alias("accuracy"),
        (F.greatest(count(y), count(~y)) / F.count("*")).alias("majority"),
        (count(y & p) / F.nullif(count(p), F.lit(0))).alias("precision"),
        (count(y & p) / F.nullif(count(y), F.lit(0))).alias("recall"),
    )
