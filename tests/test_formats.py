"""Feature tables in every format, and files of queries."""

from __future__ import annotations

import math

import pytest

from hyperslab.model import BoxQuery, FeatureSpace, query_batch
from hyperslab.sources import formats

SPACE = FeatureSpace(("id",), ("x", "y"))
SCHEMA = "id bigint, x double, y double"
ROWS = [(1, 0.1, None), (2, None, -3.5), (3, math.inf, 1e300), (4, math.nan, 0.0), (None, 1 / 3, 2.0), (1, 0.1, None)]


@pytest.fixture(scope="module")
def spark(session):
    return session


def _plain(rows):
    return sorted(repr(tuple(r)) for r in rows)


@pytest.mark.parametrize("fmt", formats.FORMATS)
def test_a_table_comes_back_as_it_was(spark, tmp_path, fmt):
    path = str(tmp_path / fmt)
    formats.store(spark.createDataFrame(ROWS, SCHEMA), path, fmt)
    assert _plain(formats.load(spark, path, fmt, SCHEMA).collect()) == _plain(ROWS)


@pytest.mark.parametrize("fmt", formats.FORMATS)
def test_a_table_without_rows(spark, tmp_path, fmt):
    path = str(tmp_path / fmt)
    formats.store(spark.createDataFrame([], SCHEMA), path, fmt)
    back = formats.load(spark, path, fmt, SCHEMA)
    assert back.columns == ["id", "x", "y"] and back.count() == 0


def test_unknown_formats_and_malformed_rows_fail(spark, tmp_path):
    with pytest.raises(ValueError):
        formats.load(spark, str(tmp_path), "text", SCHEMA)
    (tmp_path / "bad.csv").write_text("id,x,y\n1,one,2\n")
    with pytest.raises(Exception, match="(?i)malformed"):
        formats.load(spark, str(tmp_path / "bad.csv"), "csv", SCHEMA).collect()


def test_queries_come_back_as_they_were(spark, tmp_path):
    several = [(1, "a", BoxQuery.of(x=(0.1, 1 / 3))), (2, "b", BoxQuery.of(x=(None, 5.0), y=2.0)), (3, "c", BoxQuery()), (1, "a", BoxQuery.of(y=(7.0, None)))]
    batch = query_batch(spark, several, SPACE)
    formats.queries_to(batch, str(tmp_path / "q"), SPACE)
    assert _plain(formats.queries_from(spark, str(tmp_path / "q"), SPACE).collect()) == _plain(batch.collect())


def test_query_lines_by_hand(spark, tmp_path):
    file = tmp_path / "queries.json"
    file.write_text('{"query_id": 1, "template": "t", "box": {"y": {"hi": 2}}}\n{"query_id": 2, "box": null}\n')
    got = {r["query_id"]: (r["template"], r["lo"], r["hi"]) for r in formats.queries_from(spark, str(file), SPACE).collect()}
    assert got == {1: ("t", [None, None], [None, 2.0]), 2: (None, [None, None], [None, None])}
    file.write_text('{"query_id": 1, "template": "t", "box": {"z": {"hi": 2}}}\n')
    with pytest.raises(Exception, match="no such dimensions: z"):
        formats.queries_from(spark, str(file), SPACE).collect()
