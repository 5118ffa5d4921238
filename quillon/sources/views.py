"""Transaction views of the given tables: one row a transaction, with its distinct items sorted."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

VIEWS = ("order_brand", "order_word", "part_attr", "line_attr", "order_attr", "part_snation", "user_key", "user_day", "doc_word", "conv_word", "page_tag", "emb_bin")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _rows(keys: DataFrame, cells: DataFrame) -> DataFrame:
    """(tid, items): every key, also those without a cell."""
    sets = cells.groupBy("tid").agg(F.collect_set("item").alias("items"))
    return keys.join(sets, "tid", "left").select("tid", F.array_sort(F.coalesce("items", F.array().cast("array<string>"))).alias("items"))


def _attributes(source: DataFrame, tid: Column, *items: Column) -> DataFrame:
    """(tid, items) of a table whose rows are the transactions; no shuffle."""
    return source.select(tid.alias("tid"), F.array_sort(F.array_distinct(F.filter(F.array(*items), lambda x: x.isNotNull()))).alias("items"))


def item(name: str, value: Column) -> Column:
    return F.concat(F.lit(name + "="), value.cast("string"))


def band(value: Column, width: int) -> Column:
    return F.floor((value - 1) / width).cast("int")


def terms(text: Column) -> Column:
    """Lower-cased runs of four letters or more."""
    return F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit(r"(\p{L}{4,})"), 1)


def transactions(spark: SparkSession, sf_dir: str, view: str) -> DataFrame:
    """(tid, items array<string>) of a view; tid is null where rows have no key. Empty transactions stay."""
    t = lambda name: table(spark, sf_dir, name)
    if view in ("order_brand", "order_word"):
        parts = t("part")
        of = F.array("p_brand") if view == "order_brand" else F.array("p_type", F.split_part("p_name", F.lit(" "), F.lit(1)), F.split_part("p_name", F.lit(" "), F.lit(2)))
        named = parts.select(F.col("p_partkey").alias("l_partkey"), of.alias("of"))
        cells = t("lineitem").select("l_orderkey", "l_partkey").join(named, "l_partkey").select(F.col("l_orderkey").alias("tid"), F.explode("of").alias("item"))
        return _rows(t("orders").select(F.col("o_orderkey").alias("tid")), cells)
    if view == "part_attr":
        name = lambda k: F.split_part("p_name", F.lit(" "), F.lit(k))
        return _attributes(t("part"), F.col("p_partkey"), item("brand", F.col("p_brand")), item("type", F.col("p_type")), item("n1", name(1)), item("n2", name(2)), item("size", band(F.col("p_size"), 10)))
    if view == "line_attr":
        cents = lambda c: F.round(F.col(c) * 100).cast("int")
        return _attributes(t("lineitem"), F.lit(None).cast("long"), item("rf", F.col("l_returnflag")), item("ls", F.col("l_linestatus")), item("disc", cents("l_discount")), item("tax", cents("l_tax")), item("ln", F.col("l_linenumber")), item("q", band(F.col("l_quantity"), 10)))
    if view == "order_attr":
        buyers = t("customer").join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).select(F.col("c_custkey").alias("o_custkey"), "c_mktsegment", "n_name")
        joined = t("orders").join(buyers, "o_custkey", "left")
        return _attributes(joined, F.col("o_orderkey"), item("st", F.col("o_orderstatus")), item("pr", F.col("o_orderpriority")), item("y", F.year("o_orderdate")), item("m", F.month("o_orderdate")), item("seg", F.col("c_mktsegment")), item("n", F.col("n_name")))
    if view == "part_snation":
        homes = t("supplier").join(t("nation"), F.col("s_nationkey") == F.col("n_nationkey")).select(F.col("s_suppkey").alias("l_suppkey"), F.col("n_name").alias("item"))
        cells = t("lineitem").select(F.col("l_partkey").alias("tid"), "l_suppkey").join(homes, "l_suppkey").select("tid", "item")
        return _rows(t("part").select(F.col("p_partkey").alias("tid")), cells)
    if view == "user_key":
        cells = t("events").select(F.col("user_id").alias("tid"), F.get_json_object("props", "$.k").alias("item"))
        return _rows(cells.select("tid").distinct(), cells.where("item is not null"))
    if view == "user_day":
        rows = t("events").select(F.concat_ws("|", "user_id", F.date_format("ts", "yyyy-MM-dd")).alias("tid"), F.explode(F.array("event_type", item("h", F.floor(F.hour("ts") / 6)))).alias("item"))
        return _rows(rows.select("tid").distinct(), rows)
    if view == "doc_word":
        return t("documents").select(F.col("doc_id").alias("tid"), F.array_sort(F.array_distinct(terms(F.col("text")))).alias("items"))
    if view == "conv_word":
        items = F.array_union(terms(F.col("text")), F.array(item("role", F.col("role"))))
        return t("conversations").select(F.concat_ws("|", "conv_id", "turn").alias("tid"), F.array_sort(F.array_distinct(items)).alias("items"))
    if view == "page_tag":
        tags = F.regexp_extract_all("html", F.lit("<([a-z][a-z0-9]*)"), 1)
        return t("pages").select(F.col("page_id").alias("tid"), F.array_sort(F.array_distinct(tags)).alias("items"))
    if view == "emb_bin":
        bins = [item(f"d{i}", F.when(F.element_at("embedding", i) < -0.1, 1).when(F.element_at("embedding", i) < 0, 2).when(F.element_at("embedding", i) < 0.1, 3).otherwise(4)) for i in range(1, 13)]
        return _attributes(t("embeddings"), F.col("vec_id"), *bins, item("label", F.col("label")))
    raise ValueError(f"no view {view!r}; there are {', '.join(VIEWS)}")
