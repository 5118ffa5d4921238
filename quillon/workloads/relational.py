"""The relational operators, functions, streams and extensions around the methods."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.scores import kl2_value
from ..operators.bag import margins, pair_supports, triple_supports
from ..sources import synth
from ..sources.views import table, transactions
from ..streaming.baskets import window_counts
from .ranking import _ranked, ranked_pairs
from .sqlparts import cells, kl, pairs

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


@query("scan_filter_project", "SELECT l_orderkey, l_partkey FROM lineitem WHERE l_quantity >= 45 AND l_returnflag = 'R'")
def scan_filter_project(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").where("l_quantity >= 45 AND l_returnflag = 'R'").select("l_orderkey", "l_partkey")


@query("basket_join", "SELECT r_name, n_name, count(DISTINCT o_orderkey) AS orders, count(*) AS lines FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey JOIN lineitem ON l_orderkey = o_orderkey GROUP BY ALL")
def basket_join(spark, sf_dir):
    t = lambda n: table(spark, sf_dir, n)
    j = t("orders").join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return j.join(t("lineitem"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("r_name", "n_name").agg(F.countDistinct("o_orderkey").alias("orders"), F.count("*").alias("lines"))


@query("dictionary_encode", f"WITH {cells('order_word')} SELECT item, supp, row_number() OVER (ORDER BY supp DESC, item) - 1 AS item_id FROM margin")
def dictionary_encode(spark, sf_dir):
    m = margins(transactions(spark, sf_dir, "order_word"))
    return m.select("item", "supp", (F.row_number().over(Window.orderBy(F.desc("supp"), "item")) - 1).cast("long").alias("item_id"))


@query("empty_transactions", "SELECT o_orderkey AS tid FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def empty_transactions(spark, sf_dir):
    return transactions(spark, sf_dir, "order_word").where(F.size("items") == 0).select("tid")


@query("orders_without_lines", "SELECT o_orderkey FROM orders ANTI JOIN lineitem ON o_orderkey = l_orderkey")
def orders_without_lines(spark, sf_dir):
    return table(spark, sf_dir, "orders").join(table(spark, sf_dir, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select("o_orderkey")


@query("pair_supports", f"WITH {cells('order_brand')}, {pairs()} SELECT a, b, supp FROM pair")
def pair_supports_query(spark, sf_dir):
    return pair_supports(transactions(spark, sf_dir, "order_brand"))


@query("triple_supports", f"WITH {cells('user_day')} SELECT x.item AS a, y.item AS b, z.item AS c, count(*) AS supp FROM cells x JOIN cells y ON x.tid = y.tid AND x.item < y.item JOIN cells z ON x.tid = z.tid AND y.item < z.item GROUP BY ALL")
def triple_supports_query(spark, sf_dir):
    return triple_supports(transactions(spark, sf_dir, "user_day"))


_LEVELS = f"""WITH {cells('user_day')}, {pairs()}, s AS (SELECT item AS key, 1 AS size, supp FROM margin UNION ALL SELECT a || '|' || b, 2, supp FROM pair
UNION ALL SELECT x.item || '|' || y.item || '|' || z.item, 3, count(*) FROM cells x JOIN cells y ON x.tid = y.tid AND x.item < y.item JOIN cells z ON x.tid = z.tid AND y.item < z.item GROUP BY x.item, y.item, z.item),
f AS (SELECT key, size, supp, string_split(key, '|') AS items FROM s WHERE supp >= 200)"""


def _levels(spark, sf_dir):
    rows = transactions(spark, sf_dir, "user_day")
    one = margins(rows).select(F.array("item").alias("items"), "supp")
    two = pair_supports(rows).select(F.array("a", "b").alias("items"), "supp")
    three = triple_supports(rows).select(F.array("a", "b", "c").alias("items"), "supp")
    return one.union(two).union(three).where("supp >= 200").select(F.concat_ws("|", "items").alias("key"), F.size("items").alias("size"), "supp", "items")


@query("frequent_itemsets", _LEVELS + " SELECT key, size, supp FROM f")
def frequent_itemsets(spark, sf_dir):
    """Frequent itemsets of up to three items, by FP-growth."""
    from pyspark.ml.fpm import FPGrowth

    rows = transactions(spark, sf_dir, "user_day")
    found = FPGrowth(itemsCol="items", minSupport=200 / rows.count() - 1e-12).fit(rows.select("items")).freqItemsets
    return found.where(F.size("items") <= 3).select(F.concat_ws("|", F.array_sort("items")).alias("key"), F.size("items").alias("size"), F.col("freq").alias("supp"))


@query("frequent_count", _LEVELS + " SELECT size, count(*) AS itemsets FROM f GROUP BY size")
def frequent_count(spark, sf_dir):
    return frequent_itemsets(spark, sf_dir).groupBy("size").agg(F.count("*").alias("itemsets"))


@query("constrained_candidates", _LEVELS + " SELECT key, supp FROM f WHERE size = 2 AND supp >= 500")
def constrained_candidates(spark, sf_dir):
    return _levels(spark, sf_dir).where("size = 2 AND supp >= 500").select("key", "supp")


def _supersets(levels: DataFrame) -> DataFrame:
    """(key, supp, bigger, bigger_supp): itemsets with one item more, by an equi-join on what is left without it."""
    up = levels.select(F.col("key").alias("bigger"), F.col("supp").alias("bigger_supp"), F.explode(F.transform("items", lambda x: F.concat_ws("|", F.array_remove("items", x)))).alias("key"))
    return levels.join(up, "key", "left")


@query("containment_join", _LEVELS + " SELECT f.key AS small, g.key AS large FROM f JOIN f g ON g.size = f.size + 1 AND list_has_all(g.items, f.items)")
def containment_join(spark, sf_dir):
    return _supersets(_levels(spark, sf_dir)).where("bigger IS NOT NULL").select(F.col("key").alias("small"), F.col("bigger").alias("large"))


@query("band_join", "WITH b(name, lo, hi) AS (VALUES ('small', 1, 15), ('medium', 16, 35), ('large', 36, 50)) SELECT name, count(*) AS parts FROM part JOIN b ON p_size BETWEEN lo AND hi GROUP BY name")
def band_join(spark, sf_dir):
    bands = spark.createDataFrame([("small", 1, 15), ("medium", 16, 35), ("large", 36, 50)], "name string, lo int, hi int")
    return table(spark, sf_dir, "part").join(F.broadcast(bands), F.col("p_size").between(F.col("lo"), F.col("hi"))).groupBy("name").agg(F.count("*").alias("parts"))


@query("asof_event", "SELECT p.event_id, (SELECT max(v.ts) FROM events v WHERE v.user_id = p.user_id AND v.event_type = 'view' AND v.ts < p.ts) AS last_view FROM events p WHERE p.event_type = 'purchase'")
def asof_event(spark, sf_dir):
    """The last view before each purchase: a window over users and time, no range join."""
    before = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(Window.unboundedPreceding, -1)
    e = table(spark, sf_dir, "events").withColumn("last_view", F.max(F.when(F.col("event_type") == "view", F.col("ts"))).over(before))
    return e.where("event_type = 'purchase'").select("event_id", "last_view")


_MARGIN_JOIN = "FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _customers(spark, sf_dir):
    t = lambda n: table(spark, sf_dir, n)
    return t("customer").join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"))


@query("margins_cube", f"SELECT r_name, c_mktsegment, count(*) AS n {_MARGIN_JOIN} GROUP BY CUBE (r_name, c_mktsegment)")
def margins_cube(spark, sf_dir):
    return _customers(spark, sf_dir).cube("r_name", "c_mktsegment").agg(F.count("*").alias("n"))


@query("margins_rollup", f"SELECT r_name, n_name, count(*) AS n {_MARGIN_JOIN} GROUP BY ROLLUP (r_name, n_name)")
def margins_rollup(spark, sf_dir):
    return _customers(spark, sf_dir).rollup("r_name", "n_name").agg(F.count("*").alias("n"))


@query("margins_grouping_sets", f"SELECT r_name, c_mktsegment, count(*) AS n {_MARGIN_JOIN} GROUP BY GROUPING SETS ((r_name), (c_mktsegment))")
def margins_grouping_sets(spark, sf_dir):
    return _customers(spark, sf_dir).groupingSets([["r_name"], ["c_mktsegment"]], "r_name", "c_mktsegment").agg(F.count("*").alias("n"))


@query("binary_matrix", f"WITH {cells('user_day')} SELECT rws.tid, " + ", ".join(f"(count(*) FILTER (item = '{x}'))::INT AS {x}" for x in ("click", "view", "error")) + " FROM rws LEFT JOIN cells ON rws.tid = cells.tid GROUP BY rws.tid")
def binary_matrix(spark, sf_dir):
    return transactions(spark, sf_dir, "user_day").select("tid", *(F.array_contains("items", x).cast("int").alias(x) for x in ("click", "view", "error")))


@query("approx_items")
def approx_items(spark, sf_dir):
    return transactions(spark, sf_dir, "doc_word").select(F.explode("items").alias("item")).agg(F.approx_count_distinct("item").alias("items"))


@query("rank_within_view", f"WITH {cells('part_attr')} SELECT split_part(item, '=', 1) AS kind, item, dense_rank() OVER (PARTITION BY split_part(item, '=', 1) ORDER BY supp DESC)::INT AS place FROM margin")
def rank_within_view(spark, sf_dir):
    kind = F.split_part("item", F.lit("="), F.lit(1))
    return margins(transactions(spark, sf_dir, "part_attr")).select(kind.alias("kind"), "item", F.dense_rank().over(Window.partitionBy(kind).orderBy(F.desc("supp"))).alias("place"))


@query("quartile_bins", "SELECT p_partkey, ntile(4) OVER (ORDER BY p_retailprice, p_partkey)::INT AS bin FROM part")
def quartile_bins(spark, sf_dir):
    return table(spark, sf_dir, "part").select("p_partkey", F.ntile(4).over(Window.orderBy("p_retailprice", "p_partkey")).alias("bin"))


@query("topk_pairs", f"WITH {cells('order_brand')}, {pairs()} SELECT a, b, supp FROM pair ORDER BY supp DESC, a, b LIMIT 10")
def topk_pairs(spark, sf_dir):
    return pair_supports(transactions(spark, sf_dir, "order_brand")).orderBy(F.desc("supp"), "a", "b").limit(10)


@query("topk_per_item", f"WITH {cells('order_brand')}, {pairs()} SELECT a, b, supp FROM (SELECT *, row_number() OVER (PARTITION BY a ORDER BY supp DESC, b) AS k FROM pair) WHERE k <= 3")
def topk_per_item(spark, sf_dir):
    k = F.row_number().over(Window.partitionBy("a").orderBy(F.desc("supp"), "b"))
    return pair_supports(transactions(spark, sf_dir, "order_brand")).withColumn("k", k).where("k <= 3").drop("k")


_TOP = f"WITH {cells('user_day')}, {pairs()}, x AS (SELECT a, b FROM pair ORDER BY supp DESC, a, b LIMIT 12), y AS (SELECT a, b FROM pair ORDER BY supp, a, b LIMIT 30)"


def _lists(spark, sf_dir):
    p = pair_supports(transactions(spark, sf_dir, "user_day"))
    return p.orderBy(F.desc("supp"), "a", "b").limit(12).select("a", "b"), p.orderBy("supp", "a", "b").limit(30).select("a", "b")


@query("list_union", _TOP + " SELECT * FROM x UNION SELECT * FROM y")
def list_union(spark, sf_dir):
    x, y = _lists(spark, sf_dir)
    return x.union(y).distinct()


@query("list_intersect", _TOP + " SELECT * FROM x INTERSECT SELECT * FROM y")
def list_intersect(spark, sf_dir):
    x, y = _lists(spark, sf_dir)
    return x.intersect(y)


@query("list_except", _TOP + " SELECT * FROM x EXCEPT ALL SELECT * FROM y")
def list_except(spark, sf_dir):
    x, y = _lists(spark, sf_dir)
    return x.exceptAll(y)


@query("bitmap_support", f"WITH {cells('user_day')} SELECT item, supp FROM margin")
def bitmap_support(spark, sf_dir):
    """Supports as counted bits of one bitmap for each item and chunk of rows."""
    rows = transactions(spark, sf_dir, "user_day").select(F.row_number().over(Window.orderBy("tid")).cast("long").alias("k"), "items").select("k", F.explode("items").alias("item"))
    chunks = rows.groupBy("item", F.bitmap_bucket_number("k").alias("chunk")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("k")).alias("bits"))
    return chunks.groupBy("item").agg(F.sum(F.bitmap_count("bits")).alias("supp"))


@query("json_items", "SELECT json_extract_string(props, '$.k') AS k, count(*) AS n FROM events GROUP BY ALL")
def json_items(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy(F.from_json("props", "k string")["k"].alias("k")).agg(F.count("*").alias("n"))


@query("token_items", f"WITH {cells('doc_word')} SELECT item, supp FROM margin, nn WHERE supp >= 0.05 * n")
def token_items(spark, sf_dir):
    rows = transactions(spark, sf_dir, "doc_word")
    return margins(rows).join(F.broadcast(rows.agg(F.count("*").alias("n")))).where("supp >= 0.05 * n").select("item", "supp")


@query("html_tags", f"WITH {cells('page_tag')} SELECT item, supp FROM margin")
def html_tags(spark, sf_dir):
    return margins(transactions(spark, sf_dir, "page_tag"))


@query("date_items", "SELECT year(o_orderdate)::INT AS y, month(o_orderdate)::INT AS m, count(*) AS n FROM orders GROUP BY ALL")
def date_items(spark, sf_dir):
    return table(spark, sf_dir, "orders").groupBy(F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m")).agg(F.count("*").alias("n"))


@query("array_algebra", f"WITH {cells('user_day')}, r AS (SELECT tid, list(item ORDER BY item) AS items FROM cells GROUP BY tid) SELECT tid, array_to_string(list_sort(list_filter(items, lambda x: NOT list_contains(['click', 'view'], x))), '|') AS rest, len(list_intersect(items, ['click', 'h=1'])) AS common FROM r")
def array_algebra(spark, sf_dir):
    lit = lambda *xs: F.array(*map(F.lit, xs))
    return transactions(spark, sf_dir, "user_day").select("tid", F.concat_ws("|", F.array_except("items", lit("click", "view"))).alias("rest"), F.size(F.array_intersect("items", lit("click", "h=1"))).cast("long").alias("common"))


@query("supporting_rows", f"WITH {cells('part_snation')}, {pairs()}, best AS (SELECT a, b FROM pair ORDER BY supp DESC, a, b LIMIT 1) SELECT x.tid FROM cells x JOIN cells y ON x.tid = y.tid JOIN best ON x.item = a AND y.item = b")
def supporting_rows(spark, sf_dir):
    """The transactions behind the commonest pair."""
    rows = transactions(spark, sf_dir, "part_snation")
    best = pair_supports(rows).orderBy(F.desc("supp"), "a", "b").limit(1)
    return rows.join(F.broadcast(best), F.array_contains("items", F.col("a")) & F.array_contains("items", F.col("b"))).select("tid")


@query("udf_kl", _ranked("user_day") + f" SELECT a, b, round({kl('fr', 'est')}, 9) AS kl FROM k")
def udf_kl(spark, sf_dir):
    """The surprise as an Arrow function."""
    f = F.pandas_udf(_kl_series, T.DoubleType())
    return ranked_pairs(transactions(spark, sf_dir, "user_day")).select("a", "b", F.round(f("fr", "est"), 9).alias("kl"))


def _kl_series(x: pd.Series, y: pd.Series) -> pd.Series:
    return x.combine(y, kl2_value)


def _entropy(cnt: pd.Series) -> float:
    import numpy as np

    p = cnt / cnt.sum()
    return float(-(p * np.log2(p)).sum())


@query("udaf_entropy", "WITH c AS (SELECT event_type, count(*)::DOUBLE AS cnt FROM events GROUP BY ALL) SELECT round(-sum(cnt / s * log2(cnt / s)), 9) AS bits FROM c, (SELECT sum(cnt) AS s FROM c)")
def udaf_entropy(spark, sf_dir):
    f = F.pandas_udf(_entropy, T.DoubleType())
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.count("*").alias("cnt")).agg(F.round(f(F.col("cnt")), 9).alias("bits"))


def _window_sql(every: str) -> str:
    return f"SELECT time_bucket(INTERVAL '{every}', ts, TIMESTAMP '1970-01-01') AS start, event_type, count(*) AS cnt FROM events GROUP BY ALL"


@query("tumbling_baskets", _window_sql("6 hours"))
def tumbling_baskets(spark, sf_dir):
    return window_counts(table(spark, sf_dir, "events"), F.window("ts", "6 hours"))


@query("sliding_baskets", "SELECT time_bucket(INTERVAL '6 hours', ts, TIMESTAMP '1970-01-01') - k * INTERVAL '6 hours' AS start, event_type, count(*) AS cnt FROM events, (VALUES (0), (1)) t(k) GROUP BY ALL")
def sliding_baskets(spark, sf_dir):
    return window_counts(table(spark, sf_dir, "events"), F.window("ts", "12 hours", "6 hours"))


@query("session_baskets", "WITH g AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL '1 hour' THEN 0 ELSE 1 END AS new FROM events), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts) AS start, count(*) AS cnt FROM s GROUP BY user_id, k")
def session_baskets(spark, sf_dir):
    w = F.session_window("ts", "1 hour")
    return table(spark, sf_dir, "events").groupBy("user_id", w.alias("w")).agg(F.count("*").alias("cnt")).select("user_id", F.col("w.start").alias("start"), "cnt")


@query("sink_roundtrip", f"WITH {cells('order_word')} SELECT item, supp FROM margin")
def sink_roundtrip(spark, sf_dir):
    """Margins written as Parquet, partitioned by run, and read back."""
    from ..sources.files import shared_folder

    run = uuid.uuid4().hex
    path = f"{shared_folder(spark)}/margins-{run}"
    margins(transactions(spark, sf_dir, "order_word")).withColumn("run_id", F.lit(run)).write.partitionBy("run_id").parquet(path)
    return spark.read.parquet(path).where(F.col("run_id") == run).select("item", "supp")


@query("basket_text_roundtrip", f"WITH {cells('order_brand')} SELECT item, supp FROM margin")
def basket_text_roundtrip(spark, sf_dir):
    """Transactions as text, one a line, items tab-separated."""
    from ..sources.files import read_baskets, shared_folder, write_baskets

    path = f"{shared_folder(spark)}/baskets-{uuid.uuid4().hex}"
    write_baskets(transactions(spark, sf_dir, "order_brand"), path)
    return margins(read_baskets(spark, path))


_UNIT = "('0x' || substr(md5(concat_ws('|', {0})), 1, 8))::BIGINT / 4294967296.0::DOUBLE"
_SYNTH = f"""WITH g AS (SELECT id, k FROM range(0, 2000) a(id), range(0, 42) b(k)),
ind AS (SELECT 'independent' AS data, k FROM g WHERE {_UNIT.format("'independent', id, k")} < 0.2::DOUBLE + 0.6::DOUBLE * k / 41),
flips AS (SELECT id, k, sum(CASE WHEN k > 0 AND NOT {_UNIT.format("'chain', id, 'k', k")} < 0.5::DOUBLE + 0.3::DOUBLE * k / 41 THEN 1 ELSE 0 END) OVER (PARTITION BY id ORDER BY k) AS n FROM g),
cha AS (SELECT 'chain' AS data, k FROM flips WHERE ({_UNIT.format("'chain', id, 'c'")} < 0.5) = (n % 2 = 0)),
mos AS (SELECT 'mosaic' AS data, k FROM g WHERE (k < 25 AND {_UNIT.format("'mosaic', id, 's' || (k // 5)")} < 0.2::DOUBLE + 0.3::DOUBLE * (k // 5) / 4) <> ({_UNIT.format("'mosaic', id, 'f' || k")} < 0.01::DOUBLE)),
dra AS (SELECT 'draws' AS data, k FROM (SELECT id, k, row_number() OVER (PARTITION BY id ORDER BY {_UNIT.format("'draws', id, k")}, k) AS place FROM g) WHERE place <= 7)
SELECT data, 'i' || lpad(k::VARCHAR, 2, '0') AS item, count(*) AS supp FROM (SELECT * FROM ind UNION ALL SELECT * FROM cha UNION ALL SELECT * FROM mos UNION ALL SELECT * FROM dra) GROUP BY ALL"""


@query("synth_margins", _SYNTH)
def synth_margins(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Margins of the four generated data sets, 2,000 rows each."""
    out = None
    for f in (synth.independent, synth.chain, synth.mosaic, synth.draws):
        one = margins(f(spark, 2000, 42)).select(F.lit(f.__name__).alias("data"), "item", "supp")
        out = one if out is None else out.union(one)
    return out


@query("sql_surface", _ranked("user_day") + " SELECT a, b, supp FROM k WHERE fr > est")
def sql_surface(spark, sf_dir):
    ranked_pairs(transactions(spark, sf_dir, "user_day")).createOrReplaceTempView("quillon_pairs")
    return spark.sql("SELECT a, b, supp FROM quillon_pairs WHERE fr > est")
