"""The experiments: the same queries through every contestant, each a forest of its structure over the same partitions.

All contestants run alike: built once and stored, their tables cached, all queries of a workload in one job, a task per
partition. Throughput is queries over the job's seconds less those of the same job without queries, which opens the
structures only. Besides seconds stand what no machine changes: dimensions compared, objects tested, nodes visited.
"""

from __future__ import annotations

import time
from collections.abc import Iterable, Sequence
from dataclasses import asdict, dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import BoxQuery, FeatureSpace
from ..operators.forest import KINDS, Forest, piece_rows, pieces
from ..shared import new_folder
from .advisor import break_even

#: The contestants and how many dimensions each compares at once when it compares several.
CONTESTANTS = {"row_scan": ("rows", 8), "column_scan": ("columns", None), "kd_tree": ("kd", 8), "r_star_tree": ("rstar", 4), "packed_r_tree": ("packed", 4), "va_file": ("va", 8)}
FAST = ("row_scan", "column_scan", "kd_tree", "packed_r_tree", "va_file")

Queries = Sequence[tuple[int, str, BoxQuery]]


@dataclass
class Result:
    experiment: str
    parameter: str
    contestant: str
    queries: int
    selectivity: float  # share of the objects, mean over the queries
    queries_per_second: float
    compared: float  # dimensions per query
    objects_tested: float  # per query
    nodes_visited: float  # per query
    build_seconds: float  # of all trees together
    space_ratio: float  # bytes of the structure and its objects over 32-bit values

    def row(self) -> dict:
        return {k: round(v, 6) if isinstance(v, float) else v for k, v in asdict(self).items()}


def _seconds(forest: Forest, queries: Queries, k: int | None, times: int = 2) -> float:
    best = float("inf")
    for _ in range(times):
        began = time.perf_counter()
        forest.work_batch(queries, k).write.format("noop").mode("overwrite").save()
        best = min(best, time.perf_counter() - began)
    return best


def contest(experiment: str, parameter: object, df: DataFrame, space: FeatureSpace, queries: Queries, *, contestants: Iterable[str] = tuple(CONTESTANTS), p: int = 8, vector: bool = True) -> list[Result]:
    """One result per contestant. vector: several dimensions at once, or one by one."""
    out = []
    for name in contestants:
        kind, lanes = CONTESTANTS[name]
        k = lanes if vector else None
        forest = Forest.build(df, space, kind, p=p).save(new_folder(df.sparkSession, f"contest-{kind}"))
        forest.trees = forest.trees.repartitionById(p, forest.trees["part"]).cache()
        n = forest.trees.groupBy().sum("n").first()[0] or 0
        opened = _seconds(forest, [], k)
        took = max(1e-3, _seconds(forest, queries, k) - opened)
        sums = forest.work_batch(queries, k).groupBy().sum("hits", "compared", "objects_tested", "nodes_visited").first()
        size, cost = forest.space_bytes().first(), forest.build_cost().first()
        forest.trees.unpersist()
        many = len(queries)
        hits, compared, tested, visited = ((v or 0) / many for v in sums)
        out.append(Result(experiment, str(parameter), name, many, hits / max(1, n), many / took, compared, tested, visited, cost["seconds"] or 0.0, (size["index_bytes"] or 0) / max(1, size["data_bytes"] or 0)))
    return out


def hits(df: DataFrame, space: FeatureSpace, queries: Queries, *, contestants: Iterable[str] = FAST, p: int = 8, lanes: Sequence[bool] = (True,)) -> DataFrame:
    """(contestant, vector, hits) of all queries together, in one pass: a part's task builds every contestant's structure
    over each piece of its rows, in a random order, and searches it with all queries, so nothing is stored.

    df: a stored or generated table. Its splits are put together to p parts where they lie; only a table of fewer splits
    is dealt by a hash of the ids.
    """
    rows = space.features(df)
    ids, names = [F.col(f"`{c}`") for c in space.ids], tuple(contestants)
    named = lambda some, *first: some.select(*first, F.xxhash64(*ids, F.lit(1)).alias("_key"), *(F.col(f"`{d}`").cast("double").alias(f"_v{j}") for j, d in enumerate(space.dims)))
    if rows.rdd.getNumPartitions() >= p:
        dealt = named(rows.coalesce(p), F.lit(0).alias("_part"))
    else:
        dealt = named(rows, F.pmod(F.xxhash64(*ids), F.lit(p)).cast("int").alias("_part")).repartitionById(p, F.col("_part")).sortWithinPartitions("_part")
    bounds = [tuple(np.array([np.nan if b is None else b for b in side], float) for side in q.bounds(space)) for _, _, q in queries if not q.is_empty]
    most, m = piece_rows(space.m), space.m

    def run(batches):
        found = {(name, vector): 0 for name in names for vector in lanes}
        for _, _, table in pieces(batches, most):
            order = np.argsort(table.column(1).to_numpy(), kind="stable")
            x = np.stack([table.column(2 + j).to_numpy()[order] for j in range(m)], axis=1)
            for name in names:
                kind, k = CONTESTANTS[name]
                made = KINDS[kind].build(x)
                for vector in lanes:
                    found[name, vector] += sum(len(KINDS[kind].search(made, lo, hi, k if vector else None)[0]) for lo, hi in bounds)
        yield pa.RecordBatch.from_pylist([{"contestant": name, "vector": vector, "hits": n} for (name, vector), n in found.items()])

    return dealt.mapInArrow(run, "contestant string, vector boolean, hits long")


def break_evens(results: Sequence[Result], *, index: str = "kd_tree", scan: str = "row_scan") -> dict[str, float | None]:
    """The selectivity at which the index falls behind the scan: by throughput, and by dimensions compared."""
    of = lambda name, value: [(r.selectivity, value(r)) for r in results if r.contestant == name and r.selectivity > 0]
    measures = {"throughput": lambda r: r.queries_per_second, "compared": lambda r: 1 / max(1e-9, r.compared)}
    return {m: break_even(of(index, f), of(scan, f)) for m, f in measures.items()}
