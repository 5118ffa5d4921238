"""Counts, margins, rankings and static baselines, by DataFrame expressions alone."""

from __future__ import annotations

import functools
import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.scores import kl2
from ..operators.bag import margins, pair_supports, triple_supports
from ..sources.files import stored
from ..sources.views import VIEWS, transactions
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


def _frequent_only(rows: DataFrame, share: float) -> DataFrame:
    """Rows with only the items that `share` of them hold; by a join, as the items may be many."""
    n = rows.count()
    kept = margins(rows).where(F.col("supp") >= share * n).select("item")
    cell = rows.select("tid", F.explode("items").alias("item")).join(kept, "item", "left_semi")
    sets = cell.groupBy("tid").agg(F.array_sort(F.collect_list("item")).alias("items"))
    return rows.select("tid").join(sets, "tid", "left").select("tid", F.coalesce("items", F.array().cast("array<string>")).alias("items"))


def ranked_pairs(rows: DataFrame) -> DataFrame:
    """All pairs that occur with frequency, independence estimate and what measures make of them."""
    rows = stored(rows.select("items"), "rows")  # one scan and grouping of the tables; counts come from the copy
    n = rows.count()
    m = stored(margins(rows), "margins")
    items = m.count()
    p = pair_supports(rows)
    p = p.join(m.select(F.col("item").alias("a"), F.col("supp").alias("sa")), "a").join(m.select(F.col("item").alias("b"), F.col("supp").alias("sb")), "b")
    p = p.withColumn("fr", F.col("supp") / n).withColumn("fa", F.col("sa") / n).withColumn("fb", F.col("sb") / n).withColumn("est", F.col("fa") * F.col("fb"))
    return p.withColumn("kl", kl2(F.col("fr"), F.col("est"))).withColumn("h", F.col("kl") - 2 * math.log2(max(items, 1)) / max(n, 1)).withColumn("n", F.lit(float(n)))


def _ranked(view: str, extra: str = "") -> str:
    return f"""WITH {cells(view)}, {pairs()}, mm AS (SELECT count(*)::DOUBLE AS m FROM margin),
r AS (SELECT a, b, pair.supp, x.supp AS sa, y.supp AS sb, pair.supp / n AS fr, x.supp / n AS fa, y.supp / n AS fb, (x.supp / n) * (y.supp / n) AS est, n, m
  FROM pair JOIN margin x ON a = x.item JOIN margin y ON b = y.item, nn, mm),
k AS (SELECT *, {kl("fr", "est")} AS kl, {kl("fr", "est")} - 2 * log2(m) / n AS h FROM r) {extra}"""


@query("rank_pool", _ranked("order_word") + " SELECT a, b, supp, round(est, 6) AS est, round(n * kl, 6) AS bits, round(h * n, 6) AS h_bits FROM k")
def rank_pool(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every pair of order_word by how much it surprises the independence model."""
    r = ranked_pairs(transactions(spark, sf_dir, "order_word"))
    return r.select("a", "b", "supp", F.round("est", 6).alias("est"), F.round(F.col("n") * F.col("kl"), 6).alias("bits"), F.round(F.col("h") * F.col("n"), 6).alias("h_bits"))


@query("pair_surprise", _ranked("user_day") + " SELECT a, b, round(kl, 9) AS kl FROM k")
def pair_surprise(spark, sf_dir):
    return ranked_pairs(transactions(spark, sf_dir, "user_day")).select("a", "b", F.round("kl", 9).alias("kl"))


@query("heuristic_rank", _ranked("order_attr") + " SELECT a, b, round(h, 9) AS h FROM k WHERE h > 0")
def heuristic_rank(spark, sf_dir):
    return ranked_pairs(transactions(spark, sf_dir, "order_attr")).where("h > 0").select("a", "b", F.round("h", 9).alias("h"))


_DOC = """frequent AS MATERIALIZED (SELECT item, supp FROM margin, nn WHERE supp >= 0.1 * n), fc AS MATERIALIZED (SELECT tid, item FROM cells SEMI JOIN frequent USING (item)),
dp AS (SELECT x.item AS a, y.item AS b, count(*) AS supp FROM fc x JOIN fc y ON x.tid = y.tid AND x.item < y.item GROUP BY ALL)"""


@query("rank_pool_docs", f"""WITH {cells("doc_word")}, {_DOC}, r AS (SELECT a, b, dp.supp, dp.supp / n AS fr, (x.supp / n) * (y.supp / n) AS est, n FROM dp JOIN frequent x ON a = x.item JOIN frequent y ON b = y.item, nn)
SELECT a, b, supp, round(n * {kl("fr", "est")}, 6) AS bits FROM r""")
def rank_pool_docs(spark, sf_dir):
    r = ranked_pairs(_frequent_only(transactions(spark, sf_dir, "doc_word"), 0.1))
    return r.select("a", "b", "supp", F.round(F.col("n") * F.col("kl"), 6).alias("bits"))


@query("rank_pool_triples", f"""WITH {cells("order_attr")}, t AS (SELECT x.item AS a, y.item AS b, z.item AS c, count(*) AS supp FROM cells x JOIN cells y ON x.tid = y.tid AND x.item < y.item JOIN cells z ON x.tid = z.tid AND y.item < z.item GROUP BY ALL HAVING count(*) >= 50),
r AS (SELECT a, b, c, t.supp, t.supp / n AS fr, (x.supp / n) * (y.supp / n) * (z.supp / n) AS est, n FROM t JOIN margin x ON a = x.item JOIN margin y ON b = y.item JOIN margin z ON c = z.item, nn)
SELECT a, b, c, supp, round(n * {kl("fr", "est")}, 6) AS bits FROM r""")
def rank_pool_triples(spark, sf_dir):
    rows = transactions(spark, sf_dir, "order_attr")
    n, m = rows.count(), margins(rows)
    t = triple_supports(rows).where("supp >= 50").withColumn("est", F.lit(1.0))
    for k in "abc":
        t = t.join(m.select(F.col("item").alias(k), (F.col("supp") / n).alias("f")), k).withColumn("est", F.col("est") * F.col("f")).drop("f")
    return t.select("a", "b", "c", "supp", F.round(n * kl2(F.col("supp") / n, F.col("est")), 6).alias("bits"))


_MEASURES = {
    "kl": ("kl", lambda: F.col("kl")),
    "lift": ("fr / est", lambda: F.col("fr") / F.col("est")),
    "leverage": ("fr - est", lambda: F.col("fr") - F.col("est")),
    "chi2": ("n * (fr - est) * (fr - est) / (est * (1 - fa) * (1 - fb))", lambda: F.col("n") * (F.col("fr") - F.col("est")) * (F.col("fr") - F.col("est")) / (F.col("est") * (1 - F.col("fa")) * (1 - F.col("fb")))),
}


def static_rank(spark: SparkSession, sf_dir: str, measure: str, view: str = "order_word", k: int = 10) -> DataFrame:
    """The static top k of a measure of deviation from independence: redundancy among them is not looked at."""
    r = ranked_pairs(transactions(spark, sf_dir, view)).withColumn("value", F.round(_MEASURES[measure][1](), 9))
    return r.orderBy(F.desc("value"), "a", "b").limit(k).select("a", "b", "value")


for _name, (_sql, _) in _MEASURES.items():
    QUERIES[f"static_rank_{_name}"] = functools.partial(static_rank, measure=_name)
    SQL[f"static_rank_{_name}"] = _ranked("order_word") + f" SELECT a, b, round({_sql}, 9) AS value FROM k ORDER BY value DESC, a, b LIMIT 10"


@query("codetable_usage", f"WITH {cells('order_word')} SELECT item, supp AS usage, round(-log2(supp / (SELECT sum(supp) FROM margin)), 9) AS code_len FROM margin")
def codetable_usage(spark, sf_dir):
    """The standard code table: single items, with usage and code length."""
    m = margins(transactions(spark, sf_dir, "order_word"))
    total = m.agg(F.sum("supp").alias("total"))
    return m.join(F.broadcast(total)).select("item", F.col("supp").alias("usage"), F.round(-F.log2(F.col("supp") / F.col("total")), 9).alias("code_len"))


@query("list_redundancy", _ranked("order_word") + """, top AS (SELECT a, b FROM k ORDER BY round(kl, 9) DESC, a, b LIMIT 10), s AS (SELECT unnest([a, b]) AS item FROM top)
SELECT count(DISTINCT item) AS distinct_items, count(*) AS slots, round(count(DISTINCT item) / count(*), 6) AS ratio FROM s""")
def list_redundancy(spark, sf_dir):
    s = static_rank(spark, sf_dir, "kl").select(F.explode(F.array("a", "b")).alias("item"))
    return s.agg(F.countDistinct("item").alias("distinct_items"), F.count("*").alias("slots")).withColumn("ratio", F.round(F.col("distinct_items") / F.col("slots"), 6))


def _bounds(fr, est, fmin, emin):
    return F.greatest(kl2(fr, emin), kl2(fmin, est))


@query("branch_bound", f"""WITH {cells('user_day')}, {pairs()}, mm AS (SELECT count(*)::DOUBLE AS m FROM margin), whole AS (SELECT count(*) / any_value(n) AS fr_full, (SELECT product(supp / n) FROM margin, nn) AS est_full FROM (SELECT tid FROM cells, mm GROUP BY tid, m HAVING count(*) = m), nn),
r AS (SELECT a, b, pair.supp / n AS fr, (x.supp / n) * (y.supp / n) AS est, coalesce(fr_full, 0) AS ff, est_full AS ef FROM pair JOIN margin x ON a = x.item JOIN margin y ON b = y.item, nn, whole)
SELECT a, b, round(greatest({kl("fr", "ef")}, {kl("ff", "est")}), 9) AS bound FROM r""")
def branch_bound_query(spark, sf_dir):
    """Of each pair what no superset's surprise exceeds, its tail being all items."""
    rows = transactions(spark, sf_dir, "user_day")
    r = ranked_pairs(rows)
    m = margins(rows)
    items, n = m.count(), rows.count()
    est = m.agg(F.product(F.col("supp") / n).alias("ef"))
    full = rows.where(F.size("items") == items).count() / n
    return r.join(F.broadcast(est)).select("a", "b", F.round(_bounds(F.col("fr"), F.col("est"), F.lit(full), F.col("ef")), 9).alias("bound"))


@query("kl_lower_bounds_gain", _ranked("order_word") + f""", g AS (SELECT a, b, kl,
  {' + '.join(f"(CASE WHEN {q} <= 0 THEN 0 ELSE {q} * log2({q} / ({e})) END)" for q, e in (("fr", "fa * fb"), ("(fa - fr)", "fa * (1 - fb)"), ("(fb - fr)", "(1 - fa) * fb"), ("(1 - fa - fb + fr)", "(1 - fa) * (1 - fb)")))} AS gain FROM k)
SELECT a, b, round(kl, 9) AS kl, round(gain, 9) AS gain, kl <= gain + 1e-12 AS holds FROM g""")
def kl_lower_bounds_gain(spark, sf_dir):
    """The one-term surprise of a pair beside its exact gain, which is never smaller: the pair's mutual information."""
    return pair_gains(ranked_pairs(transactions(spark, sf_dir, "order_word"))).select("a", "b", F.round("kl", 9).alias("kl"), F.round("gain", 9).alias("gain"), (F.col("kl") <= F.col("gain") + 1e-12).alias("holds"))


def pair_gains(r: DataFrame) -> DataFrame:
    fr, fa, fb = F.col("fr"), F.col("fa"), F.col("fb")
    cell = lambda q, e: F.when(q <= 0, 0.0).otherwise(q * F.log2(q / e))
    gain = cell(fr, fa * fb) + cell(fa - fr, fa * (1 - fb)) + cell(fb - fr, (1 - fa) * fb) + cell(1 - fa - fb + fr, (1 - fa) * (1 - fb))
    return r.withColumn("gain", gain)


@query("exact_vs_heuristic_rank", SQL["kl_lower_bounds_gain"].split("SELECT a, b, round(kl, 9)")[0] + """ SELECT a, b, row_number() OVER (ORDER BY round(kl, 9) DESC, a, b) AS by_kl, row_number() OVER (ORDER BY round(gain, 9) DESC, a, b) AS by_gain FROM g""")
def exact_vs_heuristic_rank(spark, sf_dir):
    r = pair_gains(ranked_pairs(transactions(spark, sf_dir, "order_word")))
    place = lambda c: F.row_number().over(Window.orderBy(F.desc(F.round(c, 9)), "a", "b"))
    return r.select("a", "b", place("kl").alias("by_kl"), place("gain").alias("by_gain"))


@query("summary_negative_mdl", " UNION ALL ".join(
    f"SELECT '{v}' AS view, count(*) AS pairs_over FROM ({_ranked(v)}, g AS (SELECT n, m, fr, fa, fb, {' + '.join(f'(CASE WHEN {q} <= 1e-15 THEN 0 ELSE {q} * log2({q} / ({e})) END)' for q, e in (('fr', 'fa * fb'), ('(fa - fr)', 'fa * (1 - fb)'), ('(fb - fr)', '(1 - fa) * fb'), ('(1 - fa - fb + fr)', '(1 - fa) * (1 - fb)')))} AS gain FROM k) SELECT * FROM g WHERE n * gain > log2(n) + m * log2(1 + 1 / m) + 1 + 2 * log2(m))"
    for v in ("order_brand", "part_snation", "emb_bin", "user_key")))
def summary_negative_mdl(spark, sf_dir):
    """Views without structure: no pair's exact gain pays for its description."""
    out = None
    for v in ("order_brand", "part_snation", "emb_bin", "user_key"):
        rows = transactions(spark, sf_dir, v)
        m = margins(rows).count()
        r = pair_gains(ranked_pairs(rows))
        cost = F.log2("n") + m * math.log2(1 + 1 / m) + 1 + 2 * math.log2(m)
        one = r.where(F.col("n") * F.col("gain") > cost).agg(F.count("*").alias("pairs_over")).select(F.lit(v).alias("view"), "pairs_over")
        out = one if out is None else out.union(one)
    return out


@query("view_stats", " UNION ALL ".join(
    f"SELECT '{v}' AS view, n::BIGINT AS n, a AS items, c AS cells, round(c / n / a, 6) AS density FROM (WITH {cells(v)} SELECT n, (SELECT count(*) FROM margin) AS a, (SELECT count(*) FROM cells) AS c FROM nn)"
    for v in VIEWS))
def view_stats(spark, sf_dir):
    """Rows, items, cells and density of all views; each is read once."""
    out = None
    for v in VIEWS:
        cells_ = transactions(spark, sf_dir, v).select(F.posexplode_outer("items").alias("pos", "item"))
        by_item = cells_.groupBy("item").agg(F.count("item").alias("cells"), F.sum(F.when(F.coalesce("pos", F.lit(0)) == 0, 1).otherwise(0)).alias("n"))
        one = by_item.agg(F.sum("n").alias("n"), F.count("item").alias("items"), F.sum("cells").alias("cells"))
        one = one.select(F.lit(v).alias("view"), "n", "items", "cells", F.round(F.col("cells") / F.col("n") / F.col("items"), 6).alias("density"))
        out = one if out is None else out.union(one)
    return out


@query("column_margins", f"WITH {cells('order_word')} SELECT item, supp, round(supp / n, 9) AS fr FROM margin, nn")
def column_margins(spark, sf_dir):
    rows = transactions(spark, sf_dir, "order_word")
    return margins(rows).join(F.broadcast(rows.agg(F.count("*").alias("n")))).select("item", "supp", F.round(F.col("supp") / F.col("n"), 9).alias("fr"))


_SIZES = f"WITH {cells('order_word')}, s AS (SELECT rws.tid, count(cells.item) AS k FROM rws LEFT JOIN cells ON rws.tid = cells.tid GROUP BY rws.tid)"


@query("row_margins", _SIZES + " SELECT k AS row_size, count(*) AS cnt, round(count(*) / any_value(n), 9) AS q FROM s, nn GROUP BY k")
def row_margins(spark, sf_dir):
    rows = transactions(spark, sf_dir, "order_word")
    n = rows.agg(F.count("*").alias("n"))
    return rows.groupBy(F.size("items").cast("long").alias("row_size")).agg(F.count("*").alias("cnt")).join(F.broadcast(n)).select("row_size", "cnt", F.round(F.col("cnt") / F.col("n"), 9).alias("q"))


@query("row_margin_bins", _SIZES + " SELECT k // 4 AS bin, count(*) AS cnt FROM s GROUP BY ALL")
def row_margin_bins(spark, sf_dir):
    """Row sizes in coarser bins of four."""
    return transactions(spark, sf_dir, "order_word").groupBy(F.floor(F.size("items") / 4).alias("bin")).agg(F.count("*").alias("cnt"))


@query("rows_only_estimate", _SIZES + """, q AS (SELECT k, count(*) / any_value(n) AS q FROM s, nn GROUP BY k), mm AS (SELECT count(*)::DOUBLE AS m FROM margin)
SELECT x::BIGINT AS set_size, round((SELECT sum(q * list_product(list_transform(range(0, x), lambda i: greatest(k - i, 0) / (m - i)))) FROM q, mm), 9) AS est FROM range(1, 4) r(x)""")
def rows_only_estimate(spark, sf_dir):
    """Estimate of any set of 1 to 3 items if only row sizes are known: all items are alike."""
    rows = transactions(spark, sf_dir, "order_word")
    m, n = margins(rows).count(), rows.count()
    q = rows.groupBy(F.size("items").alias("k")).agg((F.count("*") / n).alias("q"))
    parts = [q.agg(F.round(F.sum(F.col("q") * functools.reduce(lambda a, b: a * b, [F.greatest(F.col("k") - i, F.lit(0)) / (m - i) for i in range(x)])), 9).alias("est")).select(F.lit(x).cast("long").alias("set_size"), "est") for x in (1, 2, 3)]
    return functools.reduce(DataFrame.union, parts)


@query("empirical_distribution", f"WITH {cells('order_word')}, k AS (SELECT rws.tid, coalesce(string_agg(item, '|' ORDER BY item), '') AS key FROM rws LEFT JOIN cells ON rws.tid = cells.tid GROUP BY rws.tid) SELECT key, count(*) AS cnt FROM k GROUP BY key")
def empirical_distribution(spark, sf_dir):
    return transactions(spark, sf_dir, "order_word").groupBy("items").agg(F.count("*").alias("cnt")).select(F.concat_ws("|", "items").alias("key"), "cnt")


@query("empirical_entropy", f"WITH {cells('order_word')}, k AS (SELECT rws.tid, coalesce(string_agg(item, '|' ORDER BY item), '') AS key FROM rws LEFT JOIN cells ON rws.tid = cells.tid GROUP BY rws.tid), c AS (SELECT key, count(*) AS cnt FROM k GROUP BY key) SELECT round(-sum(cnt / n * log2(cnt / n)), 9) AS bits FROM c, nn")
def empirical_entropy(spark, sf_dir):
    rows = transactions(spark, sf_dir, "order_word")
    n = rows.count()
    return rows.groupBy("items").agg(F.count("*").alias("cnt")).agg(F.round(-F.sum(F.col("cnt") / n * F.log2(F.col("cnt") / n)), 9).alias("bits"))


@query("itemset_support", f"WITH {cells('user_day')}, s(key, a, b) AS (VALUES ('click|h=1', 'click', 'h=1'), ('h=2|view', 'h=2', 'view'), ('h=1|h=2', 'h=1', 'h=2')) SELECT key, count(*) AS supp, round(count(*) / any_value(n), 9) AS fr FROM s JOIN cells x ON x.item = a JOIN cells y ON y.item = b AND x.tid = y.tid, nn GROUP BY key")
def itemset_support(spark, sf_dir):
    rows = transactions(spark, sf_dir, "user_day")
    wanted = F.array(*(F.array(*map(F.lit, s)) for s in (("click", "h=1"), ("h=2", "view"), ("h=1", "h=2"))))
    hits = rows.select(F.explode(F.filter(wanted, lambda s: F.size(F.array_except(s, "items")) == 0)).alias("s"))
    n = rows.agg(F.count("*").alias("n"))
    return hits.groupBy(F.concat_ws("|", "s").alias("key")).agg(F.count("*").alias("supp")).join(F.broadcast(n)).select("key", "supp", F.round(F.col("supp") / F.col("n"), 9).alias("fr"))


@query("indicator_flags", f"WITH {cells('user_day')} SELECT rws.tid, (count(*) FILTER (item IN ('click', 'h=1')) = 2)::INT AS covers FROM rws LEFT JOIN cells ON rws.tid = cells.tid GROUP BY rws.tid")
def indicator_flags(spark, sf_dir):
    both = F.forall(F.array(F.lit("click"), F.lit("h=1")), lambda x: F.array_contains("items", x))
    return transactions(spark, sf_dir, "user_day").select("tid", both.cast("int").alias("covers"))


_HAS = lambda x: f"bool_or(item = '{x}')"


@query("generalized_support", f"WITH {cells('user_day')}, f AS (SELECT rws.tid, coalesce({_HAS('click')}, false) AS c, coalesce({_HAS('h=1')}, false) AS h, coalesce({_HAS('view')}, false) AS v FROM rws LEFT JOIN cells ON rws.tid = cells.tid GROUP BY rws.tid) SELECT 'click,-h=1,-view' AS signs, count(*) FILTER (c AND NOT h AND NOT v) AS supp FROM f UNION ALL SELECT '-click,-h=1', count(*) FILTER (NOT c AND NOT h) FROM f")
def generalized_support(spark, sf_dir):
    """Supports of patterns with absent items, by inclusion and exclusion of supports."""
    rows = transactions(spark, sf_dir, "user_day")
    has = lambda *xs: F.count(F.when(functools.reduce(lambda a, b: a & b, [F.array_contains("items", x) for x in xs]), 1))
    s = rows.agg(F.count("*").alias("n"), has("click").alias("c"), has("h=1").alias("h"), has("view").alias("v"), has("click", "h=1").alias("ch"), has("click", "view").alias("cv"), has("h=1", "view").alias("hv"), has("click", "h=1", "view").alias("chv"))
    return s.select(F.explode(F.array(F.struct(F.lit("click,-h=1,-view").alias("signs"), F.expr("c - ch - cv + chv").alias("supp")), F.struct(F.lit("-click,-h=1").alias("signs"), F.expr("n - c - h + ch").alias("supp")))).alias("r")).select("r.signs", "r.supp")


def _half(id_):
    return F.conv(F.substring(F.md5(id_.cast("string")), 1, 8), 16, 10).cast("long") % 2


_HALF = "('0x' || substr(md5(tid::VARCHAR), 1, 8))::BIGINT % 2"


@query("holdout_split", f"WITH {cells('order_word')} SELECT {_HALF} AS half, count(*) AS n FROM rws GROUP BY ALL")
def holdout_split(spark, sf_dir):
    return transactions(spark, sf_dir, "order_word").groupBy(_half(F.col("tid")).alias("half")).agg(F.count("*").alias("n"))


@query("kl_halves", f"""WITH {cells('user_day')}, k AS (SELECT rws.tid, {_HALF.replace('tid', 'rws.tid')} AS half, coalesce(string_agg(item, '|' ORDER BY item), '') AS key FROM rws LEFT JOIN cells ON rws.tid = cells.tid GROUP BY rws.tid),
c AS (SELECT key, count(*) FILTER (half = 0) + 1.0::DOUBLE AS x, count(*) FILTER (half = 1) + 1.0::DOUBLE AS y FROM k GROUP BY key), t AS (SELECT sum(x) AS sx, sum(y) AS sy FROM c)
SELECT round(sum(x / sx * log2((x / sx) / (y / sy))), 9) AS bits FROM c, t""")
def kl_halves(spark, sf_dir):
    """Divergence of one half's rows from the other's, counts smoothed by one."""
    rows = transactions(spark, sf_dir, "user_day").withColumn("half", _half(F.col("tid")))
    c = rows.groupBy("items").agg((F.count(F.when(F.col("half") == 0, 1)) + 1.0).alias("x"), (F.count(F.when(F.col("half") == 1, 1)) + 1.0).alias("y"))
    t = c.agg(F.sum("x").alias("sx"), F.sum("y").alias("sy"))
    return c.join(F.broadcast(t)).agg(F.round(F.sum(F.col("x") / F.col("sx") * F.log2((F.col("x") / F.col("sx")) / (F.col("y") / F.col("sy")))), 9).alias("bits"))


@query("bayes_shift", f"WITH {cells('order_word')} SELECT item, round(0.99::DOUBLE * supp / n + 0.01::DOUBLE * 0.5, 9) AS shifted FROM margin, nn")
def bayes_shift(spark, sf_dir):
    return column_margins(spark, sf_dir).select("item", "supp").join(F.broadcast(transactions(spark, sf_dir, "order_word").agg(F.count("*").alias("n")))).select("item", F.round(0.99 * F.col("supp") / F.col("n") + 0.01 * 0.5, 9).alias("shifted"))


@query("independence_estimate", _ranked("part_snation") + " SELECT a, b, round(est, 9) AS est, round(abs(fr - est), 9) AS error FROM k")
def independence_estimate(spark, sf_dir):
    return ranked_pairs(transactions(spark, sf_dir, "part_snation")).select("a", "b", F.round("est", 9).alias("est"), F.round(F.abs(F.col("fr") - F.col("est")), 9).alias("error"))


@query("estimate_error", _ranked("part_snation") + " SELECT count(*) AS sets, round(max(abs(fr - est)), 9) AS largest, round(avg(abs(fr - est)), 9) AS mean FROM k")
def estimate_error(spark, sf_dir):
    gap = F.abs(F.col("fr") - F.col("est"))
    return ranked_pairs(transactions(spark, sf_dir, "part_snation")).agg(F.count("*").alias("sets"), F.round(F.max(gap), 9).alias("largest"), F.round(F.avg(gap), 9).alias("mean"))


_HOLD = f"""WITH {cells('order_word')}, {pairs()}, h AS (SELECT tid, {_HALF} AS half FROM rws), hn AS (SELECT count(*) FILTER (half = 1) AS d, count(*) FILTER (half = 0)::DOUBLE AS e FROM h),
hp AS (SELECT x.item AS a, y.item AS b, count(*) FILTER (half = 1) AS f FROM cells x JOIN cells y ON x.tid = y.tid AND x.item < y.item JOIN h ON h.tid = x.tid GROUP BY ALL),
em AS (SELECT item, count(*) FILTER (half = 0) / any_value(e) AS fr FROM cells JOIN h USING (tid), hn GROUP BY item),
r AS (SELECT a, b, f, d, x.fr * y.fr AS p FROM hp JOIN em x ON a = x.item JOIN em y ON b = y.item, hn)"""


@query("stirling_gap", _HOLD + f" SELECT a, b, f, d, round(d * {kl('(f / d)', 'p')}, 6) AS bits FROM r")
def stirling_gap(spark, sf_dir):
    """On the held-out half: d times the divergence from the explored half's independence estimate."""
    r = _holdout(spark, sf_dir)
    return r.select("a", "b", "f", "d", F.round(F.col("d") * kl2(F.col("f") / F.col("d"), F.col("p")), 6).alias("bits"))


def _holdout(spark, sf_dir):
    rows = stored(transactions(spark, sf_dir, "order_word").select(_half(F.col("tid")).alias("half"), "items"), "halves")
    held, seen = rows.where("half = 1"), rows.where("half = 0")
    d, e = held.count(), seen.count()
    m = margins(seen).select("item", (F.col("supp") / e).alias("fr"))
    r = pair_supports(rows).select("a", "b").join(pair_supports(held).withColumnRenamed("supp", "f"), ["a", "b"], "left")
    r = r.join(m.select(F.col("item").alias("a"), F.col("fr").alias("x")), "a").join(m.select(F.col("item").alias("b"), F.col("fr").alias("y")), "b")
    return r.select("a", "b", F.coalesce("f", F.lit(0)).alias("f"), F.lit(d).cast("long").alias("d"), (F.col("x") * F.col("y")).alias("p"))


_BINOM = """, lf AS MATERIALIZED (SELECT k, sum(CASE WHEN k = 0 THEN 0 ELSE ln(greatest(k, 1)) END) OVER (ORDER BY k) AS v FROM range(0, (SELECT d + 1 FROM hn)) t(k)),
fl AS MATERIALIZED (SELECT list(v ORDER BY k) AS v FROM lf),
mass AS (SELECT a, b, f, d, p, k, exp(fl.v[d + 1] - fl.v[k + 1] - fl.v[d - k + 1] + k * ln(p) + (d - k) * ln(1 - p)) AS q FROM r, fl, LATERAL (SELECT unnest(range(0, d + 1)) AS k) ks),
at_f AS (SELECT a, b, q AS qf FROM mass WHERE k = f),
pv AS (SELECT a, b, any_value(f) AS f, any_value(d) AS d, least(1.0, sum(CASE WHEN f >= d * p AND k >= f THEN q WHEN f >= d * p AND k < d * p AND k < f AND q <= qf * (1 + 1e-9) THEN q WHEN f < d * p AND k <= f THEN q WHEN f < d * p AND k > d * p AND k > f AND q <= qf * (1 + 1e-9) THEN q ELSE 0 END)) AS p_value FROM mass JOIN at_f USING (a, b) GROUP BY a, b)"""


@query("binomial_pvalue", _HOLD + _BINOM + " SELECT a, b, f, d, round(p_value, 6) AS p_value FROM pv")
def binomial_pvalue(spark, sf_dir):
    """Exact two-tailed p-values on the held-out half against the explored half's independence estimates."""
    from pyspark.sql.types import DoubleType

    from ..functions.scores import binomial_two_tailed_many

    @F.pandas_udf(DoubleType())
    def p_value(f, d, p):
        import pandas as pd

        return pd.Series(binomial_two_tailed_many(f.to_numpy(), d.to_numpy(), p.to_numpy()))

    return _holdout(spark, sf_dir).withColumn("p_value", F.round(p_value("f", "d", "p"), 6)).select("a", "b", "f", "d", "p_value")


@query("bonferroni_flags", _HOLD + _BINOM + " SELECT a, b, round(p_value, 6) <= 0.05 / count(*) OVER () AS significant FROM pv")
def bonferroni_flags(spark, sf_dir):
    r = stored(binomial_pvalue(spark, sf_dir), "p_values")
    n = r.count()
    return r.select("a", "b", (F.col("p_value") <= 0.05 / n).alias("significant"))
