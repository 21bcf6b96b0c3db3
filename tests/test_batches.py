"""Batches of queries: every way gives the answers of the plain filter, whatever the number of queries and the names."""

from __future__ import annotations

import math

import numpy as np
import pytest

from hyperslab.model import BoxQuery, FeatureSpace, Interval, query_batch
from hyperslab.operators import batch
from hyperslab.operators.layout import Layout
from hyperslab.shipping import ship

NAN, INF = float("nan"), float("inf")
SPACE = FeatureSpace(("id",), ("a", "b", "c"))


@pytest.fixture(scope="module")
def spark(session):
    ship(session)
    return session


def rows_and_boxes(rng, n=300, count=60):
    odd = [NAN, None, INF, -INF, 0.0, -0.0]
    rows = [(k, *(odd[int(rng.integers(6))] if rng.random() < 0.1 else float(np.round(rng.normal(), 1)) for _ in range(3))) for k in range(n)]
    rows += [rows[0]] * 3 + [(n + k, 0.5, 0.5, 0.5) for k in range(n // 3)]  # copies, and a value that many rows share

    def interval():
        kind = rng.integers(7)
        lo, hi = sorted(np.round(rng.normal(size=2), 1).tolist())
        return [Interval(), Interval(lo), Interval(None, hi), Interval(lo, hi), Interval.point(0.5), Interval(hi, lo), Interval(-INF, INF)][kind]

    boxes = [BoxQuery({d: interval() for d in SPACE.dims if rng.random() < 0.6}) for _ in range(count)]
    return rows, [BoxQuery(), BoxQuery.of(a=(NAN, 1.0)), BoxQuery.of(c=(None, NAN)), *boxes]


def hits(rows, boxes):
    def lies(v, i):
        return i.is_free or not (v is None or math.isnan(v) or (i.lo is not None and v < i.lo) or (i.hi is not None and v > i.hi))

    return sorted((k, r[0]) for k, q in enumerate(boxes) for r in rows if not q.is_empty and all(lies(r[1 + "abc".index(d)], i) for d, i in q.box.items()))


def found(df):
    return sorted((r["query_id"], r["id"]) for r in df.select("query_id", "id").collect())


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_every_way_gives_all_hits(spark, monkeypatch, seed):
    rows, boxes = rows_and_boxes(np.random.default_rng(seed))
    df = spark.createDataFrame(rows, "id bigint, a double, b double, c double")
    sent = query_batch(spark, [(k, "x", q) for k, q in enumerate(boxes)], SPACE)
    want = hits(rows, boxes)
    assert found(batch.search_batch(df, SPACE, sent)) == want
    monkeypatch.setattr(batch, "BIN_ROWS", 20)  # salts
    for bins in (4, 64):
        assert found(batch.search_batch(df, SPACE, sent, mode="binned", bins=bins)) == want
    monkeypatch.setattr(batch, "BROADCAST_BYTES", 1)  # the switch of 'auto'
    assert found(batch.search_batch(df, SPACE, sent)) == want
    with pytest.raises(ValueError, match="broadcast"):
        batch.search_batch(df, SPACE, sent, mode="theta")
    monkeypatch.undo()
    counted = {r["query_id"]: r["n_hits"] for r in batch.shared_counts(df, SPACE, [(k, "", q) for k, q in enumerate(boxes)], chunk=7).collect()}
    assert counted == {k: sum(x == k for x, _ in want) for k in range(len(boxes))}


def test_batches_without_bounds_rows_or_queries(spark):
    df = spark.createDataFrame([(1, NAN, None, 2.0)], "id bigint, a double, b double, c double")
    free = query_batch(spark, [(5, "x", BoxQuery())], SPACE)
    for mode in ("theta", "binned"):
        assert found(batch.search_batch(df, SPACE, free, mode=mode)) == [(5, 1)]
        assert found(batch.search_batch(df.where("false"), SPACE, free, mode=mode)) == []
        assert found(batch.search_batch(df, SPACE, free.where("false"), mode=mode)) == []
    assert batch.shared_counts(df, SPACE, []).count() == 0


def test_names_of_helper_columns_may_be_dimensions(spark, tmp_path):
    space = FeatureSpace(("id",), ("leaf", "bin", "lo", "query_id"))
    data = [(k, float(k % 7), float(k % 5), float(k), float(-k)) for k in range(100)]
    df = spark.createDataFrame(data, "id bigint, leaf double, bin double, lo double, query_id double")
    q = BoxQuery.of(leaf=(2.0, 3.0), bin=(1.0, None), lo=(None, 80.0))
    want = sorted((9, r[0]) for r in data if 2 <= r[1] <= 3 and r[2] >= 1 and r[3] <= 80)
    sent = query_batch(spark, [(9, "x", q)], space)
    for mode in ("theta", "binned"):
        assert found(batch.search_batch(df, space, sent, mode=mode)) == want
    for kind in ("kd", "str", "cell", "zorder"):
        layout = Layout.write(df, space, str(tmp_path / kind), kind=kind, leaves=8)
        assert sorted(r["id"] for r in layout.search(q).collect()) == [i for _, i in want]
        assert found(layout.search_batch(sent)) == want


def test_appended_files_are_found_by_the_directory(spark, tmp_path):
    space = FeatureSpace(("id",), ("x",))
    df = spark.range(100).selectExpr("id", "cast(id as double) as x")
    layout = Layout.write(df.where("id < 60"), space, str(tmp_path / "l"), leaves=4).append(df.where("id >= 60"))
    q = BoxQuery.of(x=(50.0, 70.0))
    assert sorted(r["id"] for r in layout.search(q).collect()) == list(range(50, 71))
    work = layout.work(q).first()
    assert work["rows"] == 100 and work["leaves_visited"] < work["leaves"]
