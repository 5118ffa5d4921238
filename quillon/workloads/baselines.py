"""Randomised baselines, the closed form of chain models, file streams and the subset function."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators import tiles
from ..operators.bag import margins
from ..operators.pool import summarize_pool
from ..operators.swap import swap_pvalues as pair_pvalues
from ..operators.swap import swap_randomize
from ..operators.vertical import mine, vertical
from ..sources.files import stored
from ..sources.views import table, transactions
from ..streaming.baskets import event_stream, replayed, window_counts
from .mining import candidates_sql
from .relational import _window_sql
from .sqlparts import cells, masks, pairs

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


@query("swap_margins", f"WITH {cells('user_day')} SELECT s AS sample, item, supp FROM margin, (VALUES (0), (1), (2)) t(s)")
def swap_margins(spark, sf_dir):
    """Item supports of three randomised versions: those of the data."""
    random = swap_randomize(transactions(spark, sf_dir, "user_day"), 3)
    return random.select("sample", F.explode("items").alias("item")).groupBy("sample", "item").agg(F.count("*").alias("supp"))


@query("swap_row_sizes", f"WITH {cells('user_day')}, r AS (SELECT tid, count(*) AS size FROM cells GROUP BY tid) SELECT s AS sample, size, count(*) AS n FROM r, (VALUES (0), (1), (2)) t(s) GROUP BY ALL")
def swap_row_sizes(spark, sf_dir):
    random = swap_randomize(transactions(spark, sf_dir, "user_day"), 3)
    return random.groupBy("sample", F.size("items").cast("long").alias("size")).agg(F.count("*").alias("n"))


@query("swap_pvalues")
def swap_pvalues(spark, sf_dir):
    """Pairs of a user's day against 19 randomised versions."""
    return pair_pvalues(transactions(spark, sf_dir, "user_day"), 19)


def path_counts(rows: DataFrame, path: list[str]) -> DataFrame:
    """One row: n, the support of each item of a path, and of each two neighbours; one pass, no shuffle of rows."""
    has = lambda x: F.array_contains("items", x)
    ones = F.array(*(F.count(F.when(has(x), 1)) for x in path))
    twos = F.array(*(F.count(F.when(has(x) & has(y), 1)) for x, y in zip(path, path[1:], strict=False)))
    return rows.agg(F.count("*").alias("n"), ones.alias("ones"), twos.alias("twos"))


def _bits(counts: Column) -> Column:
    """Sum of v log2(v / n) over an array of counts."""
    return F.aggregate(counts, F.lit(0.0), lambda acc, v: acc + F.when(v > 0, v * F.log2(v / F.col("n"))).otherwise(0.0))


def path_likelihood(rows: DataFrame, path: list[str]) -> DataFrame:
    """(n, independent, chain): log-likelihoods in bits of the margins alone and with all neighbours' pairs.

    The model with the pairs of a path has a closed form, the product of its pairs over that of its inner
    items, so no blocks are made and its length is free.
    """
    got = path_counts(rows, path)
    single = F.flatten(F.transform("ones", lambda v: F.array(v, F.col("n") - v)))
    inner = F.flatten(F.transform(F.slice("ones", 2, max(len(path) - 2, 0)), lambda v: F.array(v, F.col("n") - v)))
    at = F.sequence(F.lit(1), F.lit(len(path) - 1))
    a, b, c = (lambda k: F.element_at("ones", k)), (lambda k: F.element_at("ones", k + 1)), (lambda k: F.element_at("twos", k))
    double = F.flatten(F.transform(at, lambda k: F.array(c(k), a(k) - c(k), b(k) - c(k), F.col("n") - a(k) - b(k) + c(k))))
    return got.select("n", _bits(single).alias("independent"), (_bits(double) - _bits(inner)).alias("chain"))


def path_scores(rows: DataFrame, path: list[str]) -> DataFrame:
    """(k, mdl, background): description lengths of the path's pairs and of no itemsets."""
    m = len(path)
    of_set = F.log2("n") + m * F.log2(F.lit(1 + 1 / m)) + 1 + 2 * F.log2(F.lit(m))
    found = path_likelihood(rows, path)
    return found.select(F.lit(m - 1).cast("long").alias("k"), F.round(1 - F.col("chain") + (m - 1) * of_set, 4).alias("mdl"), F.round(1 - F.col("independent"), 4).alias("background"))


def _items(rows: DataFrame) -> list[str]:
    return [r["item"] for r in margins(rows).orderBy("item").collect()]  # a path has all items; its views have few


_PATH = (
    f"WITH {cells('user_day')}, {pairs()}, o AS (SELECT item, supp, row_number() OVER (ORDER BY item) AS k, count(*) OVER () AS m FROM margin),"
    " two AS (SELECT x.supp AS a, y.supp AS b, coalesce(p.supp, 0) AS c FROM o x JOIN o y ON y.k = x.k + 1 LEFT JOIN pair p ON p.a = x.item AND p.b = y.item),"
    " two2 AS (SELECT x.k, x.supp AS a, y.supp AS b, coalesce(p.supp, 0) AS c FROM o x JOIN o y ON y.k = x.k + 1 LEFT JOIN pair p ON p.a = x.item AND p.b = y.item), v2 AS (SELECT unnest([c, a - c, b - c, n - a - b + c]) AS v, n FROM two, nn), v1 AS (SELECT unnest([supp, n - supp]) AS v, n, k, m FROM o, nn),"
    " l AS (SELECT (SELECT sum(CASE WHEN v > 0 THEN v * log2(v / n) ELSE 0 END) FROM v2) AS two, (SELECT sum(CASE WHEN v > 0 THEN v * log2(v / n) ELSE 0 END) FROM v1) AS one,"
    " (SELECT sum(CASE WHEN v > 0 THEN v * log2(v / n) ELSE 0 END) FROM v1 WHERE k > 1 AND k < m) AS mid)"
)


@query("alt_model_loglik", _PATH + " SELECT 'independent' AS model, round(one, 2) AS loglik FROM l UNION ALL SELECT 'chain', round(two - mid, 2) FROM l UNION ALL SELECT 'maximum entropy', round(two - mid, 2) FROM l UNION ALL SELECT 'every second pair', round((SELECT sum(CASE WHEN v > 0 THEN v * log2(v / n) ELSE 0 END) FROM (SELECT k, unnest([c, a - c, b - c, n - a - b + c]) AS v, n FROM two2, nn) WHERE k % 2 = 1) + (SELECT coalesce(sum(CASE WHEN v > 0 THEN v * log2(v / n) ELSE 0 END), 0) FROM v1 WHERE m % 2 = 1 AND k = m), 2) FROM l")
def alt_model_loglik(spark, sf_dir):
    """Log-likelihoods of models with item and neighbours' frequencies: the fitted one, which is the chain, beats the others."""
    import numpy as np

    from ..operators.pool import Part, entropy, free_rows
    from ..operators.vertical import vertical

    rows = transactions(spark, sf_dir, "user_day")
    path = _items(rows)
    found = path_likelihood(rows, path).first()
    v = vertical(rows.select("items"), 1)
    order = [v.items.index(x) for x in path]
    neighbours = [tuple(sorted(p)) for p in zip(order, order[1:])]
    frequency = v.supports_of(np.array(neighbours, np.int32)) / v.n
    code = lambda ids: sum(1 << i for i in ids)
    fitted = Part(tuple(range(len(path))), [(code(x), f, True) for x, f in zip(neighbours, frequency)]).fit(v.frequencies, free_rows(v.frequencies), 1e-11, 5000)
    some = Part(tuple(range(len(path))), [(code(x), f, True) for x, f in zip(neighbours[::2], frequency[::2])]).fit(v.frequencies, free_rows(v.frequencies), 1e-11, 5000)
    out = [("independent", found["independent"]), ("chain", found["chain"]), ("maximum entropy", -v.n * entropy(fitted.rows)), ("every second pair", -v.n * entropy(some.rows))]
    return spark.createDataFrame([(k, round(x, 2)) for k, x in out], "model string, loglik double")


@query("chain_model_score", _PATH + " SELECT m - 1 AS k, round(1 - two + mid + (m - 1) * (log2(n) + m * log2(1 + 1.0::DOUBLE / m) + 1 + 2 * log2(m)), 4) AS mdl, round(1 - one, 4) AS background FROM l, nn, (SELECT max(m) AS m FROM o)")
def chain_model_score(spark, sf_dir):
    """Description length of all neighbours' pairs, items in the order of their names."""
    rows = transactions(spark, sf_dir, "user_day")
    return path_scores(rows, _items(rows))


_HOURS = "rws AS (SELECT DISTINCT user_id || '|' || strftime(ts, '%Y-%m-%d') AS tid FROM events), cells AS MATERIALIZED (SELECT DISTINCT user_id || '|' || strftime(ts, '%Y-%m-%d') AS tid, 'h' || lpad(hour(ts)::VARCHAR, 2, '0') AS item FROM events), nn AS (SELECT count(*)::DOUBLE AS n FROM rws), margin AS (SELECT item, count(*) AS supp FROM cells GROUP BY item)"


@query("chain_true_score", SQL["chain_model_score"].replace(cells("user_day"), _HOURS))
def chain_true_score(spark, sf_dir):
    """The same for items that follow each other in time: the hours of a day in which a user has events."""
    events = table(spark, sf_dir, "events").select(F.concat_ws("|", "user_id", F.date_format("ts", "yyyy-MM-dd")).alias("tid"), F.concat(F.lit("h"), F.lpad(F.hour("ts").cast("string"), 2, "0")).alias("item"))
    rows = stored(events.groupBy("tid").agg(F.collect_set("item").alias("items")), "hours")
    return path_scores(rows, _items(rows))


# lists of other methods

_DAY = f"WITH {masks('user_day', 9)}, {candidates_sql(9, 9, 1)}"


@query("frequent_topk", _DAY + " SELECT name AS items, supp::BIGINT AS supp FROM cand ORDER BY supp DESC, sz, ids LIMIT 10")
def frequent_topk(spark, sf_dir):
    """The most frequent itemsets of two items or more."""
    v, pool = _day(spark, sf_dir)
    return _named(spark, v, pool.orderBy(F.desc("supp"), F.size("items"), "items").limit(10)).select("items", "supp")


@query("largest_tiles", _DAY + " SELECT name AS items, supp::BIGINT AS supp, (supp * sz)::BIGINT AS area FROM cand ORDER BY supp * sz DESC, sz, ids LIMIT 10")
def largest_tiles(spark, sf_dir):
    """The tiles of any size with the largest area."""
    v, pool = _day(spark, sf_dir)
    return _named(spark, v, tiles.largest(pool, 10))


@query("tile_cover_greedy", _DAY + """, one AS (SELECT mask, name, (supp * sz)::BIGINT AS area FROM cand ORDER BY supp * sz DESC, sz, ids LIMIT 1),
two AS (SELECT cand.mask, cand.name, cand.sz, cand.ids, (SELECT sum(cnt * (cand.sz - CASE WHEN bag.mask & one.mask = one.mask THEN bit_count(cand.mask & one.mask) ELSE 0 END)) FROM bag WHERE bag.mask & cand.mask = cand.mask)::BIGINT AS area FROM cand, one)
SELECT 1 AS step, name AS items, area FROM one UNION ALL SELECT * FROM (SELECT 2, name, area FROM two ORDER BY area DESC, sz, ids LIMIT 1)""")
def tile_cover_greedy(spark, sf_dir):
    """Two tiles, the second by the cells that the first leaves."""
    v, pool = _day(spark, sf_dir)
    found = tiles.greedy_cover(v, tiles.pool_sets(pool), 2)
    return spark.createDataFrame([(k, v.names(x), a) for k, (x, a) in enumerate(found, 1)], "step int, items string, area long")


@query("tile_information_ratio")
def tile_information_ratio(spark, sf_dir):
    """Tiles by what they tell beyond row and column margins, for what they cost; each after those before it."""
    v, pool = _day(spark, sf_dir)
    found = tiles.by_information(v, tiles.pool_sets(pool), 10)
    return spark.createDataFrame([(k, v.names(x), round(b, 3), round(r, 6)) for k, (x, b, r) in enumerate(found, 1)], "rank int, items string, bits double, ratio double")


@query("codetable_mined")
def codetable_mined(spark, sf_dir):
    """The itemsets of a code table that shortens the rows, by usage."""
    v, pool = _day(spark, sf_dir, 200)
    table, bits, alone = tiles.code_table(v, pool)
    rows = [(v.names(x), u, round(bits, 2), round(alone, 2)) for x, u in sorted(table, key=lambda e: (-e[1], e[0]))]
    return spark.createDataFrame(rows, "items string, usage long, bits double, bits_of_items double")


def _day(spark, sf_dir, min_support: int = 1):
    rows = stored(transactions(spark, sf_dir, "user_day").select("items"), "rows")
    v = vertical(rows, min_support)
    return v, mine(v)


def _named(spark, v, found: DataFrame) -> DataFrame:
    names = F.array(*map(F.lit, v.items))
    return found.withColumn("items", F.concat_ws("|", F.array_sort(F.transform("items", lambda i: F.element_at(names, i + 1)))))


def ten_best(spark, sf_dir, view: str = "conv_word", share: float = 0.05, max_size: int = 3) -> list[tuple[str, int, str]]:
    """(method, rank, items) of the first ten itemsets by four methods on one view."""
    rows = stored(transactions(spark, sf_dir, view).select("items"), "rows")
    v = vertical(rows, max(1, -int(-share * rows.count() // 1)))
    pool = mine(v, max_size)
    sets = tiles.pool_sets(pool)
    table, _, _ = tiles.code_table(v, pool)
    lists = {
        "list": [p.items for p in summarize_pool(v, pool, "bic", k=10).picks],
        "code table": [x for x, _ in sorted(table, key=lambda e: (-e[1], e[0]))[:10]],
        "largest tiles": [tuple(r["items"]) for r in tiles.largest(pool, 10).collect()],  # ten rows
        "tiles by information": [x for x, _, _ in tiles.by_information(v, sets, 10)],
    }
    return [(name, k, v.names(x)) for name, found in lists.items() for k, x in enumerate(found, 1)]


@query("topten_lists")
def topten_lists(spark, sf_dir):
    """Ten itemsets by each of four methods, of the turns of conversations."""
    return spark.createDataFrame(ten_best(spark, sf_dir), "method string, rank int, items string")


@query("topten_distinct")
def topten_distinct(spark, sf_dir):
    """Distinct items in those lists, of their places: what a list repeats."""
    found = spark.createDataFrame(ten_best(spark, sf_dir), "method string, rank int, items string")
    cells_ = found.select("method", F.explode(F.split("items", r"\|")).alias("item"))
    return cells_.groupBy("method").agg(F.countDistinct("item").alias("items"), F.count("*").alias("places"))


@query("stream_margins", _window_sql("6 hours"))
def stream_margins(spark, sf_dir):
    """Event margins of tumbling windows, kept by a stream of files."""
    return replayed(window_counts(event_stream(spark, sf_dir, late=None), F.window("ts", "6 hours")), ["start", "event_type"], "cnt")


@query("stream_sliding", "SELECT time_bucket(INTERVAL '6 hours', ts, TIMESTAMP '1970-01-01') - k * INTERVAL '6 hours' AS start, event_type, count(*) AS cnt FROM events, (VALUES (0), (1)) t(k) GROUP BY ALL")
def stream_sliding(spark, sf_dir):
    return replayed(window_counts(event_stream(spark, sf_dir, late=None), F.window("ts", "12 hours", "6 hours")), ["start", "event_type"], "cnt")


class Subsets:
    """Itemsets of a row up to a size, keys in the order of names."""

    def eval(self, items: list[str], most: int):
        for size in range(1, most + 1):
            for s in combinations(sorted(items or []), size):
                yield "|".join(s), size


@query("udtf_subsets", f"WITH {cells('user_day')}, {pairs()} SELECT item AS key, 1 AS size, supp FROM margin UNION ALL SELECT a || '|' || b, 2, supp FROM pair")
def udtf_subsets(spark, sf_dir):
    """Supports of itemsets of two items at most, by a table function."""
    spark.udtf.register("quillon_subsets", F.udtf(Subsets, returnType="key string, size int"))
    transactions(spark, sf_dir, "user_day").createOrReplaceTempView("quillon_user_day")
    return spark.sql("SELECT key, size, count(*) AS supp FROM quillon_user_day, LATERAL quillon_subsets(items, 2) GROUP BY key, size")
