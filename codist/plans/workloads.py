"""Workloads on the given tables: the same entries as DataFrames and as SQL, so that both sides agree."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.featurize import category, counted, vector, without_tags, words


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def documents(spark: SparkSession, sf_dir: str, first: int | None = None) -> DataFrame:
    """(sample_id, label, tokens): label 1 for two of the four languages."""
    tokens = words(F.col("text"))
    label = F.coalesce(F.col("lang").isin("en", "fr"), F.lit(False)).cast("int")
    return read(spark, sf_dir, "documents").select(F.col("doc_id").alias("sample_id"), label.alias("label"), (F.slice(tokens, 1, first) if first else tokens).alias("tokens"))


def labelled(spark: SparkSession, sf_dir: str, column: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents").select("doc_id", "text")
    marks = read(spark, sf_dir, "labels").select("doc_id", column)
    return docs.join(marks, "doc_id").select(F.col("doc_id").alias("sample_id"), F.col(column).alias("label"), words(F.col("text")).alias("tokens"))


def baskets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entries of orders: how many lines have each brand, type, flag, supplier and quantity."""
    orders = read(spark, sf_dir, "orders").select("o_orderkey", (F.col("o_orderpriority") != "2-HIGH").cast("int").alias("label"))
    lines = read(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_returnflag", F.col("l_quantity").cast("int").alias("qty"))
    parts = read(spark, sf_dir, "part").select("p_partkey", "p_brand", "p_type")
    held = lines.join(parts, F.col("l_partkey") == F.col("p_partkey")).join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    tokens = F.array(category("brand", F.col("p_brand")), category("type", F.col("p_type")), category("rf", F.col("l_returnflag")), category("supp", F.col("l_suppkey")), category("qty", F.col("qty")))
    return counted(held.select(F.col("o_orderkey").alias("sample_id"), "label", tokens.alias("tokens")))


def event_samples(spark: SparkSession, sf_dir: str, value: bool = False) -> DataFrame:
    return event_tokens(read(spark, sf_dir, "events"), value)


def event_tokens(events: DataFrame, value: bool = False) -> DataFrame:
    """(sample_id, label, tokens); with ``value`` also the bucket of the value, none for null."""
    k = F.from_json("props", "k INT")["k"]
    tokens = F.array(category("user", F.col("user_id")), category("k", k), category("hour", F.hour("ts")), category("dow", F.dayofweek("ts")))
    if value:
        bucket = F.when(F.col("value") < 5, 0).when(F.col("value") < 20, 1).when(F.col("value").isNotNull(), 2)
        tokens = F.concat(tokens, F.array(category("value", bucket)))
    return events.select(F.col("event_id").alias("sample_id"), (F.col("event_type") == "purchase").cast("int").alias("label"), F.filter(tokens, lambda t: t.isNotNull()).alias("tokens"))


def turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    held = read(spark, sf_dir, "conversations")
    return held.select((F.col("conv_id") * 1000 + F.col("turn")).alias("sample_id"), (F.col("role") == "assistant").cast("int").alias("label"), words(F.col("text")).alias("tokens"))


def page_samples(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "pages").select(F.col("page_id").alias("sample_id"), F.lit(None).cast("int").alias("label"), words(without_tags(F.col("html"))).alias("tokens"))


def items(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "benchmark").select(F.col("item_id").alias("sample_id"), F.lit(None).cast("int").alias("label"), words(F.col("text")).alias("tokens"))


def unlabelled(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents").select("doc_id", "text")
    rest = docs.join(read(spark, sf_dir, "labels").select("doc_id"), "doc_id", "left_anti")
    return rest.select(F.col("doc_id").alias("sample_id"), F.lit(None).cast("int").alias("label"), words(F.col("text")).alias("tokens"))


_WORDS = "regexp_extract_all(lower(coalesce({0}, '')), '[a-z0-9]+')"
_COUNT = "SELECT sample_id, f, count(*)::DOUBLE AS x, max(label)::INT AS label FROM ({0}) GROUP BY sample_id, f"


def text_sql(table: str, key: str, label: str, text: str = "text", first: int | None = None) -> str:
    tokens = _WORDS.format(text) + (f"[1:{first}]" if first else "")
    return _COUNT.format(f"SELECT {key} AS sample_id, {label} AS label, unnest({tokens}) AS f FROM {table}")


_LANG = "CASE WHEN lang IN ('en', 'fr') THEN 1 ELSE 0 END"
_BASKET = _COUNT.format(
    "SELECT o_orderkey AS sample_id, CASE WHEN o_orderpriority <> '2-HIGH' THEN 1 ELSE 0 END AS label, "
    "unnest(['brand=' || p_brand, 'type=' || p_type, 'rf=' || l_returnflag, 'supp=' || l_suppkey, 'qty=' || l_quantity::INT]) AS f "
    "FROM lineitem JOIN part ON l_partkey = p_partkey JOIN orders ON l_orderkey = o_orderkey"
)
_EVENT = (
    "SELECT event_id AS sample_id, CASE WHEN event_type = 'purchase' THEN 1 ELSE 0 END AS label, "
    "unnest(['user=' || user_id, 'k=' || regexp_extract(props, '\"k\": *(-?[0-9]+)', 1), 'hour=' || hour(ts), 'dow=' || (dayofweek(ts) + 1){0}]) AS f FROM events"
)
_BUCKET = ", 'value=' || CASE WHEN value < 5 THEN 0 WHEN value < 20 THEN 1 WHEN value IS NOT NULL THEN 2 END"
_EVENTS = _COUNT.format(_EVENT.format(""))
_EVENTS_VALUE = _COUNT.format(f"SELECT * FROM ({_EVENT.format(_BUCKET)}) WHERE f IS NOT NULL")
_DENSE = "SELECT vec_id AS sample_id, 'd' || i AS f, embedding[i + 1]::DOUBLE AS x, CASE WHEN label < 5 THEN 1 ELSE 0 END AS label FROM embeddings, range(64) AS r(i)"
PAGE_TEXT = "regexp_replace(coalesce(html, ''), '<[^>]*>', ' ', 'g')"


@dataclass(frozen=True)
class Workload:
    entries: Callable[[SparkSession, str], DataFrame]
    sql: str
    alpha: float
    #: True for the rows of the test part, as a condition that both engines read.
    test: str = "sample_id % 5 = 0"

    def train(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        return self.entries(spark, sf_dir).where(f"NOT ({self.test})")

    def held_out(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        return self.entries(spark, sf_dir).where(self.test)


WORKLOADS: dict[str, Workload] = {
    "short5": Workload(lambda s, d: counted(documents(s, d, 5)), text_sql("documents", "doc_id", _LANG, first=5), 2.0**-9),
    "lang31": Workload(lambda s, d: counted(documents(s, d)), text_sql("documents", "doc_id", _LANG), 2.0**-21),
    "quality": Workload(lambda s, d: counted(labelled(s, d, "quality")), text_sql("documents JOIN labels USING (doc_id)", "doc_id", "quality"), 2.0**-21),
    "toxic": Workload(lambda s, d: counted(labelled(s, d, "toxic")), text_sql("documents JOIN labels USING (doc_id)", "doc_id", "toxic"), 2.0**-21),
    "basket": Workload(baskets, _BASKET, 2.0**-18, "sample_id % 5 = 0"),
    "events": Workload(lambda s, d: counted(event_samples(s, d)), _EVENTS, 2.0**-11),
    "events_value": Workload(lambda s, d: counted(event_samples(s, d, value=True)), _EVENTS_VALUE, 2.0**-11),
    "dense": Workload(lambda s, d: vector(read(s, d, "embeddings").select(F.col("vec_id").alias("sample_id"), (F.col("label") < 5).cast("int").alias("label"), "embedding"), "embedding"), _DENSE, 2.0**-3),
    "role": Workload(lambda s, d: counted(turns(s, d)), text_sql("conversations", "conv_id * 1000 + turn", "CASE WHEN role = 'assistant' THEN 1 ELSE 0 END"), 2.0**-16, "floor(sample_id / 1000) % 5 = 0"),
}
