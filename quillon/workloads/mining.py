"""Summaries by full search, pools, significance and generated data, through pools of any number of items."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import scores
from ..operators.bag import bag_of
from ..operators.greedy import background, best_of_pool, small_sets, summarize
from ..operators.maxent import MaxEntModel
from ..operators.pool import PoolSummary, best_lazy, rule, start_state, summarize_pool, summarize_rows
from ..operators.vertical import Vertical, mine, vertical
from ..sources import synth
from ..sources.files import stored
from ..sources.views import item, table, transactions
from .sqlparts import CELLS, MARGINS, estimate, fit, kl, masks, row_sizes

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


_HALF = "('0x' || substr(md5(tid::VARCHAR), 1, 8))::BIGINT % 2"
for _h in (0, 1):
    CELLS[f"user_day:{_h}"] = tuple(f"SELECT * FROM ({part}) WHERE {_HALF} = {_h}" for part in CELLS["user_day"])


def candidates_sql(m: int, most: int, min_support: int) -> str:
    """CTE cand(mask, sz, ids, name, fr): all itemsets of 2 to `most` of m items with a support."""
    return (
        f"cand AS MATERIALIZED (SELECT x AS mask, bit_count(x)::INT AS sz, list_filter(range(0, {m}), lambda i: (x >> i) & 1 = 1) AS ids, (SELECT string_agg(item, '|' ORDER BY item) FROM items WHERE (x >> id) & 1 = 1) AS name, supp, supp / n AS fr "
        f"FROM (SELECT i::BIGINT AS x, (SELECT coalesce(sum(cnt), 0) FROM bag WHERE bag.mask & i = i) AS supp FROM range(0, {1 << m}) t(i) WHERE bit_count(i::BIGINT) BETWEEN 2 AND {most}), nn WHERE supp >= {min_support})"
    )


def greedy_ctes(view: str, m: int, kind: str, k: int, most: int, min_support: int = 1, sweeps: int = 60, known: str = "") -> str:
    """CTEs of a greedy list by enumeration: pick{t} has the t-th itemset and its estimate, f{t} the rows' probabilities, kept{t} whether it stays."""
    cost = f"(log2(n) + {m} * log2(1 + 1 / {m}::DOUBLE) + 1 + sz * log2({m}))" if kind == "mdl" else "(log2(n) / 2)"
    r = f"sz * log2({m}) / n" if kind == "mdl" else "0"
    ctes = [masks(view, m), candidates_sql(m, most, min_support), fit("f0", m, MARGINS + known, sweeps if known else 2)]
    chosen = known
    for t in range(1, k + 1):
        used = "".join(f" AND mask NOT IN (SELECT mask FROM pick{u})" for u in range(1, t))
        ctes.append(f"pick{t} AS MATERIALIZED (SELECT * FROM (SELECT cand.*, {kl('fr', 'est')} - {r} AS h FROM (SELECT cand.*, {estimate(f'f{t - 1}.p', 'cand.mask')} AS est FROM cand, f{t - 1} WHERE fr > 0{used}) cand, nn) WHERE h > 0 ORDER BY round(h, 12) DESC, sz, ids LIMIT 1)")
        chosen += f" UNION ALL SELECT mask, NULL::INT, fr FROM pick{t}"
        ctes.append(fit(f"f{t}", m, MARGINS + chosen, sweeps))
        gain = f"(SELECT sum(cnt * log2(f{t}.p[bag.mask + 1])) FROM bag, f{t}) - (SELECT sum(cnt * log2(f{t - 1}.p[bag.mask + 1])) FROM bag, f{t - 1})"
        before = f" AND (SELECT ok FROM kept{t - 1})" if t > 1 else ""
        ctes.append(f"kept{t} AS MATERIALIZED (SELECT {gain} > {cost}{before} AS ok, {gain} - {cost} AS drop FROM pick{t}, nn)")
    return f"WITH RECURSIVE {', '.join(ctes)}"


def listed_sql(k: int, **more) -> str:
    rows = [f"SELECT {t}::BIGINT AS rank, name AS items, round(fr, 6) AS fr, round(est, 6) AS est FROM pick{t}, kept{t} WHERE ok" for t in range(1, k + 1)]
    return greedy_ctes(k=k, **more) + " " + " UNION ALL ".join(rows)


def listed(spark: SparkSession, s: PoolSummary) -> DataFrame:
    return spark.createDataFrame([(t, s.vertical.names(p.items), round(p.support / s.vertical.n, 6), round(p.estimate, 6)) for t, p in enumerate(s.picks, 1)], "rank long, items string, fr double, est double")


def of_view(spark, sf_dir, view: str, share: float = 0.0, max_size: int | None = 4, kind: str = "mdl", k: int | None = None, **more) -> PoolSummary:
    """The list of a view over all its items and itemsets with support in `share` of the rows, and in one row at least."""
    rows = stored(transactions(spark, sf_dir, view).select("items"), "rows")
    return summarize_rows(rows, kind, max(1, math.ceil(share * rows.count())), max_size, k=k, **more)


def _register(name: str, sql: str | None = None, **more) -> None:
    QUERIES[name] = lambda spark, sf_dir: listed(spark, of_view(spark, sf_dir, **more))
    if sql:
        SQL[name] = sql


_DAY = dict(view="user_day", m=9, most=4, k=3)
_register("summary_user_day_mdl", listed_sql(kind="mdl", **_DAY), view="user_day", k=3)
_register("summary_user_day_bic", listed_sql(kind="bic", **_DAY), view="user_day", k=3, kind="bic")
#: Full searches over all items with the stated share of the rows; no SQL enumerates their 2^items rows.
_register("top_k_order_word", view="order_word", share=0.01, k=10)
_register("top_k_part_attr", view="part_attr", share=0.005, k=10, kind="bic")
_register("top_k_line_attr", view="line_attr", share=0.01, max_size=3, k=10, kind="bic")
_register("top_k_doc_word", view="doc_word", share=0.15, max_size=3, k=10)
_register("top_k_conv_word", view="conv_word", share=0.05, max_size=3, k=10)
_register("summary_order_attr", view="order_attr", share=0.002, max_size=3)
_register("summary_part_snation", view="part_snation", share=0.3, max_size=3, kind="bic")


@query("summary_doc_labels")
def summary_doc_labels(spark, sf_dir):
    """Words of labelled documents together with their classes as items: which itemsets hold a class."""
    of = table(spark, sf_dir, "labels").groupBy("doc_id").agg(F.max("quality").alias("quality"), F.max("toxic").alias("toxic"))
    classes = F.filter(F.array(item("quality", F.col("quality")), item("toxic", F.col("toxic"))), lambda x: x.isNotNull())
    rows = transactions(spark, sf_dir, "doc_word").join(of, F.col("tid") == F.col("doc_id")).select(F.array_union("items", classes).alias("items"))
    rows = stored(rows, "rows")
    s = summarize_rows(rows, "bic", max(1, math.ceil(0.05 * rows.count())), 2, k=10)
    return listed(spark, s).withColumn("has_class", F.col("items").contains("="))


def given_pool(spark, sf_dir) -> tuple[Vertical, DataFrame]:
    """A pool that is given: the itemsets of up to three items that 300 user days or more have, by FP-growth."""
    from pyspark.ml.fpm import FPGrowth

    rows = stored(transactions(spark, sf_dir, "user_day").select("items"), "rows")
    v = vertical(rows, 1)
    place = {x: k for k, x in enumerate(v.items)}
    ids = F.array_sort(F.transform("items", lambda x: F.create_map(*(c for k, p in place.items() for c in (F.lit(k), F.lit(p))))[x]))
    found = FPGrowth(itemsCol="items", minSupport=max(300 / max(v.n, 1) - 1e-12, 0.0)).fit(rows).freqItemsets.where(F.size("items").between(2, 3))
    return v, stored(found.select(ids.alias("items"), F.col("freq").alias("supp")), "given")


_POOL = dict(view="user_day", m=9, most=3, min_support=300, kind="bic")


@query("subset_from_pool", listed_sql(k=3, **_POOL))
def subset_from_pool(spark, sf_dir):
    """The best subset of a given pool, of three itemsets at most here."""
    v, pool = given_pool(spark, sf_dir)
    return listed(spark, summarize_pool(v, pool, "bic", k=3))


@query("k_subset_from_pool", listed_sql(k=1, **_POOL))
def k_subset_from_pool(spark, sf_dir):
    """The best subset of one itemset."""
    v, pool = given_pool(spark, sf_dir)
    return listed(spark, summarize_pool(v, pool, "bic", k=1))


@query("score_curve", greedy_ctes(kind="mdl", sweeps=150, **_DAY) + " SELECT 0 AS k, round(1 - (SELECT sum(cnt * log2(f0.p[bag.mask + 1])) FROM bag, f0), 1) AS score UNION ALL " + " UNION ALL ".join(
    f"SELECT {t}, round(1 - (SELECT sum(cnt * log2(f0.p[bag.mask + 1])) FROM bag, f0) - " + " - ".join(f"(SELECT drop FROM kept{u})" for u in range(1, t + 1)) + f", 1) FROM kept{t} WHERE ok" for t in (1, 2, 3)))
def score_curve(spark, sf_dir):
    """The score after each itemset."""
    s = of_view(spark, sf_dir, "user_day", k=3)
    return spark.createDataFrame([(k, round(x, 1)) for k, x in enumerate(s.curve())], "k int, score double")


_KNOWN = " UNION ALL SELECT mask, NULL::INT, fr FROM cand WHERE name IN ('click|h=1', 'purchase|view')"


@query("bg_itemsets_fit", greedy_ctes(view="user_day", m=9, kind="mdl", k=1, most=4, known=_KNOWN) + " SELECT 'score' AS what, round(1 - (SELECT sum(cnt * log2(f0.p[bag.mask + 1])) FROM bag, f0), 1) AS value UNION ALL SELECT name, round(" + estimate("f0.p", "cand.mask") + ", 6) FROM cand, f0 WHERE sz = 2 UNION ALL SELECT 'first pick ' || name, round(est, 6) FROM pick1")
def bg_itemsets_fit(spark, sf_dir):
    """An itemset and a rule (who buys also views, with that confidence) as background: in the model, not in the penalty."""
    rows = stored(transactions(spark, sf_dir, "user_day").select("items"), "rows")
    v = vertical(rows, 1)
    at = {x: k for k, x in enumerate(v.items)}
    pool = mine(v, 4)
    supp = {tuple(r["items"]): r["supp"] for r in pool.where(F.size("items") == 2).collect()}  # pairs of nine items
    pair = lambda *names: tuple(sorted(at[x] for x in names))
    known = [(pair("click", "h=1"), supp[pair("click", "h=1")] / v.n)]
    buys = float(v.frequencies[at["purchase"]])
    known += rule([at["purchase"]], [at["view"]], buys, supp[pair("purchase", "view")] / v.n / buys)
    state = start_state(v, known)
    s = summarize_pool(v, pool, "mdl", k=1, known=known)
    out = [("score", round(state.score("mdl"), 1)), *((v.names(x), round(state.estimate(x), 6)) for x in supp), *(("first pick " + v.names(p.items), round(p.estimate, 6)) for p in s.picks)]
    return spark.createDataFrame(out, "what string, value double")


@query("summary_user_day_rows", greedy_ctes(view="user_day", m=9, kind="mdl", k=2, most=3, known=f" UNION ALL {row_sizes(9)}", sweeps=120) + " " + " UNION ALL ".join(f"SELECT {t}::BIGINT AS rank, name AS items, round(fr, 6) AS fr, round(est, 5) AS est FROM pick{t}, kept{t} WHERE ok" for t in (1, 2)))
def summary_user_day_rows(spark, sf_dir):
    """The list where row sizes are known besides item frequencies."""
    b = bag_of(transactions(spark, sf_dir, "user_day"), 9)  # all its items
    s = summarize(b, "mdl", "rows+columns", k=2, max_size=3)
    return spark.createDataFrame([(t, b.names(p.items), round(p.frequency, 6), round(p.estimate, 5)) for t, p in enumerate(s.picks, 1)], "rank long, items string, fr double, est double")


@query("fit_with_row_bins", f"WITH RECURSIVE {masks('user_day', 9)}, " + fit("z", 9, f"{MARGINS} UNION ALL {row_sizes(9, 3)}", 120) + f" SELECT x.item || '|' || y.item AS items, round({estimate('z.p', '(1 << x.id) | (1 << y.id)')}, 5) AS est FROM z, items x, items y WHERE x.item < y.item")
def fit_with_row_bins(spark, sf_dir):
    """Estimates where row sizes are known in bins of three only: a weight a bin, not one a size."""
    b = bag_of(transactions(spark, sf_dir, "user_day"), 9)
    model = MaxEntModel(9, margins=b.margins, row_sizes=b.row_sizes(), bins=[j // 3 for j in range(10)]).fit(1e-11, 3000)
    return spark.createDataFrame([(b.names((1 << i) | (1 << j)), round(model.query((1 << i) | (1 << j)), 5)) for i in range(9) for j in range(i)], "items string, est double")


@query("row_margins_effect")
def row_margins_effect(spark, sf_dir):
    """The most surprising pair of whole views, with and without known row sizes, and what it tells then."""
    out = []
    for view in ("order_word", "part_snation", "part_attr"):
        b = bag_of(transactions(spark, sf_dir, view))
        if b.m < 2:
            continue
        pool = {x: s / b.n for x, s in b.supports_of(small_sets(b.m, 2)).items() if s}
        for known in ("columns", "rows+columns"):
            model = background(b, known)
            found = best_of_pool(model, pool, "bic", b.n, 10)
            out.append((view, known, b.names(found[0]) if found else None, round(found[2] * b.n, 3) if found else 0.0, model.sweeps))
    return spark.createDataFrame(out, "view string, known string, items string, bits double, sweeps int")


# a session of modelling.py: two pairs are added, the first is removed, and added again
_PAIR_COST = "(log2(n) + 9 * log2(1 + 1 / 9::DOUBLE) + 1 + 2 * log2(9))"
_BITS = "(SELECT sum(cnt * log2({0}.p[bag.mask + 1])) FROM bag, {0})"
SQL["interactive_replay"] = (
    greedy_ctes(view="user_day", m=9, kind="mdl", k=2, most=2, sweeps=120) + ", " + fit("left_", 9, MARGINS + " UNION ALL SELECT mask, NULL::INT, fr FROM pick2", 120)
    + f", v AS (SELECT 1 - {_BITS.format('f0')} AS none, 1 - {_BITS.format('f2')} + 2 * {_PAIR_COST} AS two, 1 - {_BITS.format('left_')} + {_PAIR_COST} AS one FROM nn)"
    " SELECT 'start' AS step, '' AS items, round(none, 1) AS score FROM v UNION ALL SELECT 'extend', name, round(two, 1) FROM v, pick1 UNION ALL SELECT 'extend', name, round(two, 1) FROM v, pick2"
    " UNION ALL SELECT 'remove', name, round(one, 1) FROM v, pick1 UNION ALL SELECT 'add', name, round(two, 1) FROM v, pick1"
)


@query("bic_vs_mdl_sizes")
def bic_vs_mdl_sizes(spark, sf_dir):
    """Both criteria over all items of three views."""
    out = []
    for view, share in (("user_day", 0.0), ("part_snation", 0.3), ("order_attr", 0.005)):
        for kind in ("bic", "mdl"):
            s = of_view(spark, sf_dir, view, share, 3, kind)
            out.append((view, kind, len(s.picks), round(s.score, 2), round(s.background_score, 2)))
    return spark.createDataFrame(out, "view string, criterion string, k int, score double, background double")


@query("lazy_branch_bound")
def lazy_branch_bound(spark, sf_dir):
    """The first pick by rounds of a stored frontier, with and without a seeded incumbent, beside that of the whole pool."""
    rows = stored(transactions(spark, sf_dir, "user_day").select("items"), "rows")
    v = vertical(rows, 1)
    state = start_state(v)
    pool = summarize_pool(v, mine(v, 4), "mdl", k=1)
    out = []
    for seed in (None, 1 / 8):
        found, stats = best_lazy(v, state, "mdl", 4, seed=seed)
        out.append((seed is not None, v.names(found[0]), found[0] == pool.picks[0].items, stats["rounds"], stats["visited"], stats["pruned"]))
    return spark.createDataFrame(out, "seeded boolean, items string, same boolean, rounds int, visited long, pruned long")


# significance on a held-out half

def half(tid) -> "F.Column":
    return F.conv(F.substring(F.md5(tid.cast("string")), 1, 8), 16, 10).cast("long") % 2


def halves(spark, sf_dir, view: str, share: float, max_size: int | None, kind: str = "mdl", k: int | None = None) -> tuple[PoolSummary, DataFrame, Vertical]:
    """The list of the explored half, its pool, and the bitmaps of the other half."""
    rows = stored(transactions(spark, sf_dir, view).select(half(F.coalesce(F.col("tid").cast("string"), F.concat_ws("|", "items"))).alias("half"), "items"), "halves")
    seen, held = rows.where("half = 0"), rows.where("half = 1")
    v = vertical(seen, max(1, math.ceil(share * seen.count())))
    pool = mine(v, max_size)
    return summarize_pool(v, pool, kind, k=k), pool, vertical(held, 1, like=v)


def padded(sets: list[tuple[int, ...]]) -> np.ndarray:
    width = max(map(len, sets), default=1)
    return np.array([[-1] * (width - len(x)) + list(x) for x in sets], np.int32).reshape(-1, width)


def tested(spark, held: Vertical, sets: list[tuple[int, ...]], estimates: list[float]) -> list[tuple]:
    """(items, f, d, p, p_value, significant) of itemsets on the held-out half, corrected for their number."""
    f = held.supports_of(padded(sets)) if sets else np.zeros(0, np.int64)
    value = scores.binomial_two_tailed_many(f, np.full(len(f), held.n), np.array(estimates, float)) if sets else f
    return [(held.names(x), int(a), held.n, round(float(p), 6), round(float(q), 6), bool(round(float(q), 6) <= 0.05 / len(sets))) for x, a, p, q in zip(sets, f, estimates, value, strict=True)]


_TESTED = "items string, f long, d long, p double, p_value double, significant boolean"


def against_background(spark, s: PoolSummary, held: Vertical) -> list[tuple]:
    return tested(spark, held, [p.items for p in s.picks], [float(np.prod(s.vertical.frequencies[list(p.items)])) for p in s.picks])


def against_previous(spark, s: PoolSummary, held: Vertical) -> list[tuple]:
    return tested(spark, held, [p.items for p in s.picks], [p.estimate for p in s.picks])


def against_final(spark, s: PoolSummary, pool: DataFrame, held: Vertical, sample: int = 1000) -> list[tuple]:
    """The `sample` itemsets of the pool that come first by a hash, those of the list left out, against the final model."""
    taken = spark.createDataFrame([(list(p.items),) for p in s.picks], "items array<int>")
    names = spark.sparkContext.broadcast(s.vertical.items)
    name = F.udf(lambda ids: "|".join(sorted(names.value[i] for i in ids)))
    if pool.count() > 100_000:  # a first draw by number keeps the naming of sets small
        pool = pool.orderBy(F.xxhash64("items")).limit(20 * sample)
    drawn = pool.join(taken, "items", "left_anti").orderBy(F.md5(name("items"))).limit(sample)
    sets = [tuple(r["items"]) for r in drawn.collect()]  # `sample` rows
    return tested(spark, held, sets, [s.state.estimate(x) for x in sets])


_TEST_SQL = """, hrws AS ({0}), hcells AS MATERIALIZED ({1}),
hbag AS MATERIALIZED (SELECT mask, count(*) AS cnt FROM (SELECT hrws.tid, coalesce(sum(1 << id), 0)::BIGINT AS mask FROM hrws LEFT JOIN (hcells JOIN items USING (item)) c ON hrws.tid = c.tid GROUP BY hrws.tid) GROUP BY mask),
hd AS (SELECT sum(cnt)::BIGINT AS d FROM hbag),
lf AS MATERIALIZED (SELECT list(v ORDER BY k) AS v FROM (SELECT k, sum(CASE WHEN k = 0 THEN 0 ELSE ln(greatest(k, 1)) END) OVER (ORDER BY k) AS v FROM range(0, (SELECT d + 1 FROM hd)) t(k))),
t1 AS (SELECT name AS items, (SELECT coalesce(sum(cnt), 0) FROM hbag WHERE hbag.mask & t.mask = t.mask)::BIGINT AS f, d, t.p FROM ({2}) t, hd),
t2 AS (SELECT t1.*, list_transform(range(0, d + 1), lambda k: exp(lf.v[d + 1] - lf.v[k + 1] - lf.v[d - k + 1] + k * ln(p) + (d - k) * ln(1 - p))) AS q FROM t1, lf),
t3 AS (SELECT items, f, d, p, least(1.0, list_sum(list_transform(q, lambda x, i: CASE WHEN f >= d * p AND i - 1 >= f THEN x WHEN f >= d * p AND i - 1 < d * p AND i - 1 < f AND x <= q[f + 1] * (1 + 1e-9) THEN x WHEN f < d * p AND i - 1 <= f THEN x WHEN f < d * p AND i - 1 > d * p AND i - 1 > f AND x <= q[f + 1] * (1 + 1e-9) THEN x ELSE 0 END))) AS v FROM t2)
SELECT items, f, d, round(p, 6) AS p, round(v, 6) AS p_value, round(v, 6) <= 0.05 / (SELECT count(*) FROM t3) AS significant FROM t3"""


def _test_sql(of: str) -> str:
    return greedy_ctes(view="user_day:0", m=9, kind="mdl", k=3, most=4, sweeps=100) + _TEST_SQL.format(*CELLS["user_day:1"], of)


_PICKED = " UNION ALL ".join(f"SELECT pick{t}.*, ok FROM pick{t}, kept{t} WHERE ok" for t in (1, 2, 3))
_FINAL = "(SELECT p FROM f3 WHERE (SELECT ok FROM kept3) UNION ALL SELECT p FROM f2 WHERE (SELECT ok FROM kept2) AND NOT coalesce((SELECT ok FROM kept3), false) UNION ALL SELECT p FROM f1 WHERE (SELECT ok FROM kept1) AND NOT coalesce((SELECT ok FROM kept2), false))"


@query("signif_background", _test_sql(f"SELECT name, mask, (SELECT product(items.supp / n) FROM items, nn WHERE (mask >> id) & 1 = 1) AS p FROM ({_PICKED})"))
def signif_background(spark, sf_dir):
    """The itemsets of a list of one half, on the other half, against column margins."""
    s, _, held = halves(spark, sf_dir, "user_day", 0.0, 4, k=3)
    return spark.createDataFrame(against_background(spark, s, held), _TESTED)


@query("signif_previous", _test_sql(f"SELECT name, mask, est AS p FROM ({_PICKED})"))
def signif_previous(spark, sf_dir):
    """The same against the model that the itemset was added to."""
    s, _, held = halves(spark, sf_dir, "user_day", 0.0, 4, k=3)
    return spark.createDataFrame(against_previous(spark, s, held), _TESTED)


@query("signif_unselected", _test_sql(f"SELECT name, mask, {estimate('z.p', 'cand.mask')} AS p FROM (SELECT * FROM cand WHERE mask NOT IN (SELECT mask FROM ({_PICKED})) ORDER BY md5(name) LIMIT 1000) cand, {_FINAL} z"))
def signif_unselected(spark, sf_dir):
    """A thousand itemsets that were not taken (here all), against the final model."""
    s, pool, held = halves(spark, sf_dir, "user_day", 0.0, 4, k=3)
    return spark.createDataFrame(against_final(spark, s, pool, held), _TESTED)


@query("half_vs_whole_sizes")
def half_vs_whole_sizes(spark, sf_dir):
    """Length of the list of all rows and of half of them."""
    out = []
    for view, share in (("user_day", 0.0), ("order_attr", 0.005)):
        whole = of_view(spark, sf_dir, view, share, 3)
        s, _, _ = halves(spark, sf_dir, view, share, 3)
        out.append((view, len(whole.picks), len(s.picks)))
    return spark.createDataFrame(out, "view string, k_whole int, k_half int")


@query("significance_table")
def significance_table(spark, sf_dir):
    """Counts of significant itemsets: against the background, against previous models, of unselected ones against the final model."""
    out = []
    for view, share, size in (("user_day", 0.0, 4), ("order_attr", 0.005, 3), ("part_snation", 0.3, 3)):
        s, pool, held = halves(spark, sf_dir, view, share, size)
        a, b, c = against_background(spark, s, held), against_previous(spark, s, held), against_final(spark, s, pool, held)
        out.append((view, sum(r[5] for r in a), sum(r[5] for r in b), len(s.picks), sum(r[5] for r in c), len(c)))
    return spark.createDataFrame(out, "view string, signif_background int, signif_previous int, k int, signif_unselected int, sampled int")


@query("summary_estimate_error")
def summary_estimate_error(spark, sf_dir):
    """Largest and mean gap between frequency and estimate: of the list's itemsets under the model before each, and of the whole pool under the final model."""
    from ..operators.pool import scored

    rows = stored(transactions(spark, sf_dir, "order_attr").select("items"), "rows")
    v = vertical(rows, max(1, math.ceil(0.005 * rows.count())))
    pool = mine(v, 3)
    s = summarize_pool(v, pool, "mdl")
    gap = F.abs(F.col("supp") / v.n - F.col("est"))
    every = scored(pool, s.state, "mdl").agg(F.count("*").alias("n"), F.max(gap).alias("a"), F.avg(gap).alias("b")).first()
    own = [abs(p.support / v.n - p.estimate) for p in s.picks] or [0.0]
    return spark.createDataFrame([("selected", len(s.picks), max(own), sum(own) / len(own)), ("pool under the list", every["n"], every["a"], every["b"])], "sets string, n long, largest double, mean double")


# generated data of the published sizes

#: Data set: (generator, rows, minimum support).
GENERATED = {
    "independent": (synth.independent, 100_000, 5_000),
    "markov": (synth.chain, 100_000, 5_000),
    "mosaic": (synth.mosaic, 100_000, 5_000),
    "lotto": (synth.draws, 2_386, 1),
}


def generated(spark: SparkSession, name: str, kinds=("bic", "mdl"), time_limit: float | None = None) -> list[tuple]:
    """(data, criterion, itemsets mined, k, finished, score, background, first picks, seconds) for each criterion."""
    import time

    make, n, min_support = GENERATED[name]
    began = time.monotonic()
    v = vertical(stored(make(spark, n).select("items"), "rows"), min_support)
    pool = mine(v)
    size, mined, out = pool.count(), time.monotonic() - began, []
    for kind in kinds:
        s = summarize_pool(v, pool, kind, time_limit=time_limit)
        out.append((name, kind, size, len(s.picks), s.finished, round(s.score, 1), round(s.background_score, 1), [v.names(p.items) for p in s.picks[:10]], round(mined + s.seconds, 1)))
    return out


_GENERATED = "data string, criterion string, itemsets long, k int, finished boolean, score double, background double, picks array<string>, seconds double"


def _generated(name: str):
    def run(spark, sf_dir):
        return spark.createDataFrame(generated(spark, name), _GENERATED).drop("seconds")

    run.__doc__ = f"The lists of the generated data set {name} at its published size, under both criteria."
    return run


for _name in GENERATED:
    QUERIES[f"experiment_{_name}"] = _generated(_name)


@query("experiment_time_limit")
def experiment_time_limit(spark, sf_dir):
    """A list that is stopped by its time limit comes back as far as it got, and says so."""
    rows = stored(transactions(spark, sf_dir, "user_day").select("items"), "rows")
    v = vertical(rows, 1)
    s = summarize_pool(v, mine(v, 3), "bic", time_limit=0.0)
    return spark.createDataFrame([(len(s.picks), s.finished)], "k int, finished boolean")


def summary_rows(spark, sf_dir: str, views=(("order_brand", 0.01, 3), ("order_word", 0.01, 4), ("part_attr", 0.005, 4), ("line_attr", 0.01, 3), ("order_attr", 0.005, 3), ("part_snation", 0.3, 3), ("user_key", 0.2, 3), ("user_day", 0.0, 4), ("doc_word", 0.15, 3), ("conv_word", 0.05, 3), ("page_tag", 0.01, 3), ("emb_bin", 0.01, 3)), time_limit: float = 120.0) -> list[tuple]:
    """(view, criterion, n, items, minimum support, itemsets, k, finished, seconds, score, background) of the views."""
    out = []
    for view, share, size in views:
        rows = stored(transactions(spark, sf_dir, view).select("items"), "rows")
        v = vertical(rows, max(1, math.ceil(share * rows.count())))
        pool = mine(v, size)
        for kind in ("bic", "mdl"):
            s = summarize_pool(v, pool, kind, time_limit=time_limit)
            out.append((view, kind, v.n, v.m, v.min_support, pool.count(), len(s.picks), s.finished, round(s.seconds, 1), round(s.score, 1), round(s.background_score, 1)))
    return out


@query("summary_table")
def summary_table(spark, sf_dir):
    """List length, score and background score of all views under both criteria; 60 seconds a list."""
    found = summary_rows(spark, sf_dir, time_limit=60.0)
    schema = "view string, criterion string, n long, items long, min_support long, itemsets long, k int, finished boolean, seconds double, score double, background double"
    return spark.createDataFrame(found, schema).drop("seconds")

