"""What the second review found: work that held too much at once, and answers that changed with the table's size."""

from __future__ import annotations

import time

import duckdb
import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from hyperslab import queries
from hyperslab.model import BoxQuery, FeatureSpace
from hyperslab.operators import batch, forest, rtree
from hyperslab.operators.forest import Forest
from hyperslab.operators.predicate import box_predicate
from hyperslab.shipping import ship
from hyperslab.sources import datagen, workload

SMALL = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def spark(session):
    ship(session)
    return session


def agrees(spark, name):
    with duckdb.connect() as db:
        for table in ("lineitem", "orders", "customer", "supplier", "part", "events"):
            db.execute(f"CREATE VIEW {table} AS SELECT * FROM '{SMALL}/{table}.parquet'")
        want = sorted(db.execute(queries.ORACLES[name]).fetchall())
    return sorted(map(tuple, queries.QUERIES[name](spark, SMALL).collect())) == want


def test_pieces_of_a_part_are_bounded_and_one_tree():
    rows = [(0, 1), (0, 2), (0, 3), (0, 4), (0, 5), (1, 6), (1, 7)]
    batches = [pa.RecordBatch.from_pylist([{"part": p, "v": v} for p, v in some]) for some in (rows[:3], rows[3:])]
    got = [(part, piece, t.column("v").to_pylist()) for part, piece, t in forest.pieces(iter(batches), 2)]
    assert got == [(0, 0, [1, 2]), (0, 1, [3, 4]), (0, 2, [5]), (1, 0, [6, 7])]
    assert all(forest.piece_rows(m) * m * 8 <= forest.PIECE_BYTES for m in (3, 5, 19, 50, 100))


@pytest.mark.parametrize("kind", ["kd", "kd_median", "packed", "va", "columns", "rows"])
def test_trees_in_pieces_answer_and_count_alike(spark, monkeypatch, kind):
    monkeypatch.setattr(forest, "PIECE_BYTES", 100 * 3 * 8)
    df, space = datagen.uniform(spark, 3000, 3), FeatureSpace(("id",), ("d0", "d1", "d2"))
    q = BoxQuery.of(d0=(0.2, 0.7), d1=(0.1, 0.9))
    made = Forest.build(df.where("id < 2000"), space, kind, p=2).append(df.where("id >= 2000"), p=2)
    assert made.trees.agg(F.max("n")).first()[0] <= 100 and made.trees.count() > 25
    assert sorted(r["id"] for r in made.search(q).collect()) == sorted(r["id"] for r in df.where(box_predicate(q, space)).select("id").collect())
    assert {r["metric"]: r["value"] for r in made.work(q).collect()}["trees"] == made.build_cost().first()["trees"] == 4


def test_scan_work_counts_parts_whatever_their_size(spark, monkeypatch):
    monkeypatch.setattr(forest, "PIECE_BYTES", 100 * 5 * 8)
    assert agrees(spark, "scan_work")


def test_counts_of_many_blocks(spark, monkeypatch):
    monkeypatch.setattr(batch, "BLOCK_BYTES", 64 * 3 * 8)
    space = FeatureSpace(("id",), ("d0", "d1", "d2"))
    df = datagen.uniform(spark, 2000, 3).withColumn("d1", F.when(F.col("id") % 9 > 0, F.col("d1")))
    boxes = [(k, "t", q) for k, q in enumerate([*workload.target_boxes(space, 0.1, 5), BoxQuery(), BoxQuery.of(d0=(0.9, 0.1)), BoxQuery.of(d1=(None, 0.5))])]
    want = {k: n for k, _, q in boxes if not q.is_empty and (n := df.where(box_predicate(q, space)).count())}
    assert {r["query_id"]: r["n_hits"] for r in batch.scan_counts(df, space, boxes).collect()} == want


def test_picked_rows_of_equal_ids_are_all_found(spark):
    space = FeatureSpace(("id",), ("a",))
    df = spark.createDataFrame([(k // 3, float(k)) for k in range(60)] + [(None, -1.0)], "id bigint, a double")
    rows = space.features(df)
    found = workload.rows_at(rows, space, spark.range(61).withColumnRenamed("id", "place"), workload._numbered(rows, space), True).collect()
    assert [x for _, (x,) in sorted((r["place"], r["x"]) for r in found)] == [-1.0, *map(float, range(60))]


@pytest.mark.parametrize("name", ["contest_sensor", "contest_threads", "contest_clusters"])
def test_contests_build_and_search_in_one_pass(spark, monkeypatch, name):
    monkeypatch.setattr(Forest, "save", None)
    assert agrees(spark, name)


@pytest.mark.parametrize("name", ["io_break_even", "row_scan_empty_box"])
def test_queries_read_their_table(spark, name):
    df = queries.QUERIES[name](spark, SMALL)
    assert "lineitem.parquet" in df._jdf.queryExecution().executedPlan().toString() and agrees(spark, name)


class Plain(rtree._Inserter):
    """Takes the volumes of all entries and the overlaps of all their pairs at every choice."""

    def _choose(self, node, box):
        m = len(box) // 2
        lo, hi = node.used()[:m].T.copy(), -node.used()[m:].T
        a, b = np.minimum(lo, box[:m]), np.maximum(hi, -box[m:])
        before = rtree._volume(lo, hi)
        added = np.zeros((len(lo), 1))
        if self.star and node.level == 1:
            added = rtree._overlap(a[:, None], b[:, None], lo[None], hi[None]) - rtree._overlap(lo[:, None], hi[:, None], lo[None], hi[None])
            np.fill_diagonal(added, 0)
        k = int(np.lexsort((before, rtree._volume(a, b) - before, np.round(added.sum(axis=1), 12)))[0])
        node.put(k, np.concatenate((a[k], -b[k])))
        return k


@pytest.mark.parametrize("m, whole", [(5, False), (3, True), (20, False)])
def test_insertion_makes_the_plain_rules_tree_in_less_time(m, whole):
    x = np.random.default_rng(m).random((4000, m))
    x = np.floor(x * 9) / 9 if whole else x
    took, trees = [], []
    for kind in (rtree._Inserter, Plain):
        began = time.process_time()
        root = kind(x, x, rtree.CAPACITY, True).build()
        took.append(time.process_time() - began)
        trees.append(rtree.arrays(rtree.RTree(root, x, x)))
    assert all(np.array_equal(trees[0][k], trees[1][k]) for k in trees[0])
    assert 1.3 * took[0] < took[1]
