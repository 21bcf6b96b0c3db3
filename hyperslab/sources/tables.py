"""Feature tables over the given tables, in Spark and as the same SQL."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.encode import dictionary_codes, epoch_days, epoch_seconds
from ..model import FeatureSpace

LINE_KEY = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice")


@dataclass(frozen=True)
class Features:
    """A feature table: its space, and the SQL that yields ids and dimensions."""

    name: str
    space: FeatureSpace
    sql: str
    build: object

    def df(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        return self.build(spark, sf_dir)


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


_DAY = "CAST(datediff('day', DATE '1970-01-01', CAST(l_shipdate AS DATE)) AS DOUBLE)"


def _line5(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", F.col("l_quantity").alias("quantity"), F.col("l_extendedprice").alias("price"), F.col("l_discount").alias("discount"), F.col("l_tax").alias("tax"), epoch_days("l_shipdate").alias("day"))


LINE5 = Features(
    "line5",
    FeatureSpace(LINE_KEY, ("quantity", "price", "discount", "tax", "day")),
    f"SELECT {', '.join(LINE_KEY)}, l_quantity AS quantity, l_extendedprice AS price, l_discount AS discount, l_tax AS tax, {_DAY} AS day FROM lineitem",
    _line5,
)


def _events3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "events").select("event_id", epoch_seconds("ts").alias("second"), F.col("user_id").cast("double").alias("user"), F.col("value").alias("value"))


EVENTS3 = Features("events3", FeatureSpace(("event_id",), ("second", "user", "value")), "SELECT event_id, CAST(epoch_us(ts) AS DOUBLE) / 1000000.0::DOUBLE AS second, CAST(user_id AS DOUBLE) AS user, value FROM events", _events3)


def embedding(m: int) -> Features:
    """The first m coordinates of the embeddings."""
    dims = tuple(f"e{j}" for j in range(m))

    def build(spark: SparkSession, sf_dir: str) -> DataFrame:
        return read(spark, sf_dir, "embeddings").select("vec_id", *(F.col("embedding")[j].cast("double").alias(f"e{j}") for j in range(m)))

    return Features(f"emb{m}", FeatureSpace(("vec_id",), dims), f"SELECT vec_id, {', '.join(f'CAST(embedding[{j + 1}] AS DOUBLE) AS e{j}' for j in range(m))} FROM embeddings", build)


#: The 19 dimensions, with the column each takes; codes are ranks of strings.
WIDE_DIMS = {
    "nation": "c_nationkey", "day": "l_shipdate", "quantity": "l_quantity", "price": "l_extendedprice", "discount": "l_discount", "tax": "l_tax", "status": "l_linestatus_code",
    "size": "p_size", "order_status": "o_orderstatus_code", "flag": "l_returnflag_code", "type": "p_type_code", "brand": "p_brand_code", "segment": "c_mktsegment_code",
    "priority": "o_orderpriority_code", "customer": "o_custkey", "supplier": "l_suppkey", "part": "l_partkey", "line": "l_linenumber", "supplier_nation": "s_nationkey",
}
_CODED = {"lineitem": ("l_linestatus", "l_returnflag"), "orders": ("o_orderstatus", "o_orderpriority"), "part": ("p_type", "p_brand"), "customer": ("c_mktsegment",)}


def _wide19(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem joined with its four partners. Spark picks the joins by size: small partners broadcast themselves."""
    t = {n: dictionary_codes(read(spark, sf_dir, n), _CODED.get(n, ())) for n in ("lineitem", "orders", "customer", "part", "supplier")}
    joined = (
        t["lineitem"].join(t["orders"], F.col("l_orderkey") == F.col("o_orderkey")).join(t["customer"], F.col("o_custkey") == F.col("c_custkey")).join(t["part"], F.col("l_partkey") == F.col("p_partkey")).join(t["supplier"], F.col("l_suppkey") == F.col("s_suppkey"))
    )
    return joined.select(*LINE_KEY, *((epoch_days(c) if d == "day" else F.col(c).cast("double")).alias(d) for d, c in WIDE_DIMS.items()))


def _wide_sql() -> str:
    codes = {c: f"(SELECT {c} AS v, dense_rank() OVER (ORDER BY {c}) AS k FROM (SELECT DISTINCT {c} FROM {t} WHERE {c} IS NOT NULL))" for t, cs in _CODED.items() for c in cs}
    joins = " ".join(f"LEFT JOIN {sql} AS x_{c} ON x_{c}.v = {c}" for c, sql in codes.items())
    dims = ", ".join(f"{_DAY if d == 'day' else f'CAST(x_{c[:-5]}.k AS DOUBLE)' if c.endswith('_code') else f'CAST({c} AS DOUBLE)'} AS {d}" for d, c in WIDE_DIMS.items())
    return f"SELECT {', '.join(LINE_KEY)}, {dims} FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey {joins}"


WIDE19 = Features("wide19", FeatureSpace(LINE_KEY, tuple(WIDE_DIMS)), _wide_sql(), _wide19)


def _correlated(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "lineitem").select(*LINE_KEY, F.col("l_extendedprice").alias("price"), (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("revenue"), F.col("l_quantity").alias("quantity"))


CORRELATED3 = Features("correlated3", FeatureSpace(LINE_KEY, ("price", "revenue", "quantity")), f"SELECT {', '.join(LINE_KEY)}, l_extendedprice AS price, l_extendedprice * (1 - l_discount) AS revenue, l_quantity AS quantity FROM lineitem", _correlated)


def _docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = dictionary_codes(read(spark, sf_dir, "documents").select("doc_id", "lang", "n_chars"), ["lang"])
    return rows.join(read(spark, sf_dir, "labels"), "doc_id", "left").select("doc_id", F.col("n_chars").cast("double").alias("chars"), F.col("lang_code").alias("language"), F.col("quality").cast("double").alias("quality"), F.col("toxic").cast("double").alias("toxic"))


DOCS4 = Features(
    "docs4",
    FeatureSpace(("doc_id",), ("chars", "language", "quality", "toxic")),
    "SELECT d.doc_id, CAST(n_chars AS DOUBLE) AS chars, CAST(x.k AS DOUBLE) AS language, CAST(quality AS DOUBLE) AS quality, CAST(toxic AS DOUBLE) AS toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id LEFT JOIN (SELECT lang AS v, dense_rank() OVER (ORDER BY lang) AS k FROM (SELECT DISTINCT lang FROM documents WHERE lang IS NOT NULL)) AS x ON x.v = lang",
    _docs,
)


def _pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "pages").select("page_id", F.char_length("html").cast("double").alias("size"), F.char_length("url").cast("double").alias("url_size"), F.regexp_count("html", F.lit("<a ")).cast("double").alias("links"))


PAGES3 = Features("pages3", FeatureSpace(("page_id",), ("size", "url_size", "links")), "SELECT page_id, CAST(length(html) AS DOUBLE) AS size, CAST(length(url) AS DOUBLE) AS url_size, CAST(len(regexp_extract_all(html, '<a ')) AS DOUBLE) AS links FROM pages", _pages)


def _conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "conversations").select("conv_id", F.col("turn").alias("turn_no"), F.col("turn").cast("double").alias("turn"), F.char_length("text").cast("double").alias("size"))


TURNS2 = Features("turns2", FeatureSpace(("conv_id", "turn_no"), ("turn", "size")), "SELECT conv_id, turn AS turn_no, CAST(turn AS DOUBLE) AS turn, CAST(length(text) AS DOUBLE) AS size FROM conversations", _conversations)


def _benchmark(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "benchmark").select("item_id", F.char_length("text").cast("double").alias("size"), F.regexp_count("text", F.lit(" ")).cast("double").alias("gaps"))


BENCH2 = Features("bench2", FeatureSpace(("item_id",), ("size", "gaps")), "SELECT item_id, CAST(length(text) AS DOUBLE) AS size, CAST(len(regexp_extract_all(text, ' ')) AS DOUBLE) AS gaps FROM benchmark", _benchmark)
