"""Models, scores, redundancy and summaries: the engine works by blocks, the SQL by enumerating all rows."""

from __future__ import annotations

import functools

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import scores
from ..operators import blocks as B
from ..operators import sizes as Z
from ..operators.bag import Bag, bag_of, wide_bag_of
from ..operators.greedy import Session, background, best_by_gain, find_best, model_score, optimal_subset, small_sets, summarize
from ..operators.maxent import MaxEntModel
from ..operators.partition import partition_items
from ..sources.views import transactions
from .sqlparts import MARGINS, estimate, fit, kl, masks, name_of, row_sizes, support

QUERIES: dict = {}
SQL: dict[str, str] = {}

#: The running example: items a to h, three itemsets with frequencies.
EXAMPLE = (("abc", 0.5), ("cd", 0.4), ("def", 0.8))
ITEMS = "abcdefgh"


def letters(text: str) -> int:
    return sum(1 << ITEMS.index(c) for c in text)


MEMBERS = [letters(s) for s, _ in EXAMPLE]
FREQUENCIES = [f for _, f in EXAMPLE]


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def frame(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def bag(spark: SparkSession, sf_dir: str, view: str, m: int) -> Bag:
    return bag_of(transactions(spark, sf_dir, view), m)


def example_model() -> MaxEntModel:
    return MaxEntModel(8, MEMBERS, FREQUENCIES).fit(1e-12, 5000)


_EXAMPLE = "VALUES " + ", ".join(f"({x}, NULL::INT, {f}::DOUBLE)" for x, f in zip(MEMBERS, FREQUENCIES, strict=True))
_EX_FIT = f"WITH RECURSIVE {fit('f', 8, f'SELECT * FROM ({_EXAMPLE}) v(mask, size, fr)', 150)}"
_STATES = "s AS (SELECT i::BIGINT AS row, p[i + 1] AS q FROM f, LATERAL (SELECT unnest(range(0, len(p))) AS i))"
_EX_SIG = "(CASE WHEN row & {0} = {0} THEN 1 ELSE 0 END + CASE WHEN row & {1} = {1} THEN 2 ELSE 0 END + CASE WHEN row & {2} = {2} THEN 4 ELSE 0 END)".format(*MEMBERS)


# the same model's parts on a view: the most frequent pairs of its items are the collection

_POOL = f"pool AS MATERIALIZED (SELECT x, s, row_number() OVER (ORDER BY s DESC, x) - 1 AS k FROM (SELECT x, {support('x')} AS s FROM (SELECT ((1 << a.id) | (1 << b.id))::BIGINT AS x FROM items a, items b WHERE a.id < b.id) t)), mem AS MATERIALIZED (SELECT k, x, s FROM pool WHERE k < 3)"
_SIG = "sum(CASE WHEN row & mem.x = mem.x THEN 1 << mem.k ELSE 0 END)::BIGINT"
_SIGNED = f"WITH RECURSIVE {masks('user_day', 9)}, {_POOL}, pr AS (SELECT id, supp / n AS p FROM items, nn), s AS (SELECT i::BIGINT AS row, product(CASE WHEN (i >> id) & 1 = 1 THEN p ELSE 1 - p END) AS q FROM range(0, 512) t(i), pr GROUP BY i), g AS MATERIALIZED (SELECT row, q, {_SIG} AS sig FROM s, mem GROUP BY row, q), b AS (SELECT DISTINCT sig AS block FROM g)"


def frequent_pairs(b: Bag) -> list[tuple[int, int]]:
    """(pair, support), the most frequent first."""
    return sorted(b.supports_of(small_sets(b.m, 2)).items(), key=lambda e: (-e[1], e[0]))


def _day_members(spark, sf_dir) -> tuple[Bag, list[int]]:
    b = bag(spark, sf_dir, "user_day", 9)
    return b, [x for x, _ in frequent_pairs(b)[:3]]


def _day_blocks(spark, sf_dir):
    b, sets = _day_members(spark, sf_dir)
    blocks = B.closed_blocks(sets)
    return sets, blocks, B.cumulative(blocks, B.independent_mass(b.margins))


def _masses(spark, got) -> DataFrame:
    return frame(spark, [(k, round(float(v[0]), 9) + 0.0) for k, v in got.items()], "block long, mass double")  # no negative zeros


_DAY_FIT = f"WITH RECURSIVE {masks('user_day', 9)}, {_POOL}, {fit('f', 9, 'SELECT x AS mask, NULL::INT AS size, s / n AS fr FROM mem, nn', 150)}"


def _day_model(spark, sf_dir) -> tuple[Bag, MaxEntModel]:
    """The model of three frequent pairs over even rows."""
    b = bag(spark, sf_dir, "user_day", 9)
    sets = frequent_pairs(b)[:3]
    return b, MaxEntModel(b.m, [x for x, _ in sets], [s / b.n for _, s in sets]).fit(1e-12, 5000)


@query("fit_small_collection", _DAY_FIT + f""", {_STATES}, g AS (SELECT row, q, {_SIG} AS sig FROM s, mem GROUP BY row, q), v AS (SELECT sig, any_value(q) AS q FROM g GROUP BY sig), base AS (SELECT q AS z FROM v WHERE sig = 0)
SELECT 'norm' AS what, round(z * 512, 6) AS value FROM base UNION ALL SELECT {name_of('x')}, round(q / z, 5) FROM mem JOIN v ON sig = 1 << k, base""")
def fit_small_collection(spark, sf_dir):
    """Multipliers and constant of the model of three frequent pairs."""
    b, model = _day_model(spark, sf_dir)
    return frame(spark, [("norm", round(1 / model.total(), 6)), *((b.names(x), round(u, 5)) for x, u in zip(model.members, model.mult, strict=True))], "what string, value double")


def _ask(model: MaxEntModel, sets: list[str]) -> list[tuple]:
    return [(s, round(model.query(letters(s)), 6)) for s in sets]


_ASKED = ["agh", "a", "b", "c", "d", "e", "f", "g", "h", "ad", "abcdef", "be"]


@query("query_estimates", _EX_FIT + " " + " UNION ALL ".join(f"SELECT '{s}' AS items, round({estimate('p', str(letters(s)))}, 6) AS est FROM f" for s in _ASKED))
def query_estimates(spark, sf_dir):
    return frame(spark, _ask(example_model(), _ASKED), "items string, est double")


@query("model_blocks", _EX_FIT + f", {_STATES} SELECT {_EX_SIG}::BIGINT AS block, round(sum(q), 6) AS prob FROM s GROUP BY ALL")
def model_blocks(spark, sf_dir):
    return frame(spark, [(b, round(p, 6)) for _, b, p in example_model().blocks()], "block long, prob double")


@query("row_probability", _EX_FIT + f", {_STATES} SELECT row, round(q, 9) AS p FROM s")
def row_probability(spark, sf_dir):
    """Probability of each of the 256 rows, from the parameters, as one expression."""
    model = example_model()
    p = F.lit(1 / model.total() / 256)
    for x, u in zip(model.members, model.mult, strict=True):
        p = p * F.when(F.col("row").bitwiseAND(F.lit(x).cast("long")) == x, u).otherwise(1.0)
    return spark.range(256).withColumnRenamed("id", "row").select("row", F.round(p, 9).alias("p"))


@query("closed_blocks", _SIGNED + " SELECT block FROM b")
def closed_blocks(spark, sf_dir):
    return frame(spark, [(k,) for k in _day_blocks(spark, sf_dir)[1]], "block long")


@query("block_cumulative", _SIGNED + " SELECT block, round(sum(q), 9) AS mass FROM b JOIN g ON sig & block = block GROUP BY block")
def block_cumulative(spark, sf_dir):
    return _masses(spark, _day_blocks(spark, sf_dir)[2])


@query("block_sizes_quick", _SIGNED + " SELECT sig AS block, round(sum(q), 9) AS mass FROM g GROUP BY ALL")
def block_sizes_quick(spark, sf_dir):
    return _masses(spark, B.quick_sizes(*_day_blocks(spark, sf_dir))[0])


@query("block_sizes_quadratic", _SIGNED + " SELECT sig AS block, round(sum(q), 9) AS mass FROM g GROUP BY ALL")
def block_sizes_quadratic(spark, sf_dir):
    return _masses(spark, B.quadratic_sizes(*_day_blocks(spark, sf_dir)[1:])[0])


@query("block_subtractions", _SIGNED + f""", un AS (SELECT block, coalesce(bit_or(x), 0)::BIGINT AS items FROM b LEFT JOIN mem ON (block >> k) & 1 = 1 GROUP BY block),
u AS (SELECT block, k AS i, items | x AS row FROM un, mem WHERE (block >> k) & 1 = 0), led AS (SELECT block, i, {_SIG} AS onto FROM u, mem GROUP BY block, i, row)
SELECT 'quick' AS method, count(*) FILTER (onto & ((1 << i) - 1) = block & ((1 << i) - 1)) AS subtractions FROM led UNION ALL SELECT 'quadratic', count(*) FROM b x JOIN b y ON x.block <> y.block AND x.block & y.block = y.block""")
def block_subtractions(spark, sf_dir):
    """The cost of both ways to exact block sizes."""
    sets, blocks, cumulative = _day_blocks(spark, sf_dir)
    return frame(spark, [("quick", B.quick_sizes(sets, blocks, cumulative)[1]), ("quadratic", B.quadratic_sizes(blocks, cumulative)[1])], "method string, subtractions long")


@query("closure_table", _SIGNED + f", r AS (SELECT i::BIGINT AS start, coalesce(bit_or(x), 0)::BIGINT AS row FROM range(0, 8) t(i) LEFT JOIN mem ON (i >> k) & 1 = 1 GROUP BY i), c AS (SELECT start, {_SIG} AS closed FROM r, mem GROUP BY start, row) SELECT start, j, (start | (closed & (7 - ((1 << j) - 1))))::BIGINT AS closed FROM c, (SELECT i::INT AS j FROM range(0, 4) t(i))")
def closure_table(spark, sf_dir):
    """All subcollections of three frequent pairs, closed; after the first j members only later ones are added (j = 0: all)."""
    _, sets = _day_members(spark, sf_dir)
    return frame(spark, [(k, j, B.closure_after(k, sets, j)) for k in range(8) for j in range(4)], "start long, j int, closed long")


@query("block_histogram", "WITH RECURSIVE " + masks("user_day", 9) + ", c(k, x, y) AS (VALUES (0, 'click', 'h=1'), (1, 'view', 'h=2'), (2, 'error', 'h=0')), m AS (SELECT k, sum(1 << id)::BIGINT AS mask FROM c JOIN items ON item IN (x, y) GROUP BY k) SELECT sig, sum(cnt)::BIGINT AS rows FROM (SELECT bag.mask, cnt, sum(CASE WHEN bag.mask & m.mask = m.mask THEN 1 << k ELSE 0 END)::BIGINT AS sig FROM bag, m GROUP BY bag.mask, cnt) GROUP BY sig")
def block_histogram(spark, sf_dir):
    """Observed rows by the members of a collection that they contain."""
    b = bag(spark, sf_dir, "user_day", 9)
    sig = functools.reduce(lambda a, k: a + F.when(F.col("mask").bitwiseAND(F.lit(k[1]).cast("long")) == k[1], 1 << k[0]).otherwise(0), enumerate([b.mask("click", "h=1"), b.mask("view", "h=2"), b.mask("error", "h=0")]), F.lit(0))
    return b.rows.groupBy(sig.cast("long").alias("sig")).agg(F.sum("cnt").alias("rows"))


@query("itemset_groups", f"WITH RECURSIVE {masks('user_day', 9)}, p AS (SELECT ((1 << a.id) | (1 << b.id))::BIGINT AS x, a.supp AS sa, b.supp AS sb FROM items a, items b WHERE a.id < b.id), s AS MATERIALIZED (SELECT x, {name_of('x')} AS name FROM (SELECT x, {support('x')} * n - sa * sb AS gain FROM p, nn) ORDER BY gain DESC, x LIMIT 6), e AS (SELECT a.x AS a, b.x AS b FROM s a JOIN s b ON a.x & b.x <> 0), r AS (SELECT x AS a, x AS b FROM s UNION SELECT r.a, e.b FROM r JOIN e ON r.b = e.a) SELECT y.name AS items, min(z.name) AS part FROM r JOIN s y ON y.x = r.a JOIN s z ON z.x = r.b GROUP BY y.name")
def itemset_groups(spark, sf_dir):
    """The six pairs furthest above independence by item-disjoint part, named by its first."""
    b = bag(spark, sf_dir, "user_day", 9)
    gain = {x: s * b.n - math.prod(b.supports[i] for i in range(b.m) if x >> i & 1) for x, s in b.supports_of(small_sets(b.m, 2)).items()}
    sets = sorted(gain, key=lambda x: (-gain[x], x))[:6]
    names = [b.names(x) for x in sets]
    return frame(spark, [(names[k], min(names[j] for j in ks)) for ks in B.groups(sets) for k in ks], "items string, part string")


@query("remove_itemset", f"WITH RECURSIVE {fit('f', 8, f'SELECT * FROM ({_EXAMPLE}) v(mask, size, fr) WHERE mask <> {MEMBERS[1]}', 60)} SELECT x AS items, est FROM (" + " UNION ALL ".join(f"SELECT '{s}' AS x, round({estimate('p', str(letters(s)))}, 6) AS est FROM f" for s in ("cd", "ad", "agh")) + ")")
def remove_itemset(spark, sf_dir):
    return frame(spark, _ask(example_model().without_set(MEMBERS[1]), ["cd", "ad", "agh"]), "items string, est double")


@query("entropy_drop", _DAY_FIT + f", {_STATES} SELECT round(9 + sum(CASE WHEN q > 0 THEN q * log2(q) ELSE 0 END), 6) AS bits FROM s")
def entropy_drop(spark, sf_dir):
    """Entropy of the even rows less that of the model of three frequent pairs: the divergence between them."""
    return frame(spark, [(round(9 - _day_model(spark, sf_dir)[1].entropy(), 6),)], "bits double")


_P3 = "p(k, v) AS (VALUES (1, 0.5::DOUBLE), (2, 0.25::DOUBLE), (3, 0.1::DOUBLE), (4, 0.95::DOUBLE), (5, 0.7::DOUBLE))"
_PROBS = [0.5, 0.25, 0.1, 0.95, 0.7]
_SIZE_SQL = f"WITH {_P3}, s AS (SELECT i::BIGINT AS row, product(CASE WHEN (i >> (k - 1)) & 1 = 1 THEN v ELSE 1 - v END) AS q FROM range(0, 32) t(i), p GROUP BY i)"


def _sizes(spark, values):
    return frame(spark, [(j, round(float(q), 9)) for j, q in enumerate(values)], "row_size long, prob double")


@query("size_distribution", _SIZE_SQL + " SELECT bit_count(row)::BIGINT AS row_size, round(sum(q), 9) AS prob FROM s GROUP BY ALL")
def size_distribution(spark, sf_dir):
    return _sizes(spark, Z.size_distribution(_PROBS))


@query("size_distribution_updated", _SIZE_SQL.replace("0.95::DOUBLE", "0.6::DOUBLE") + " SELECT bit_count(row)::BIGINT AS row_size, round(sum(q), 9) AS prob FROM s GROUP BY ALL")
def size_distribution_updated(spark, sf_dir):
    """One probability changes from 0.95 to 0.6: updated in linear time, the SQL from scratch."""
    return _sizes(spark, Z.updated(Z.size_distribution(_PROBS), 0.95, 0.6))


@query("size_distribution_given", _SIZE_SQL + " , c AS (SELECT bit_count(row)::BIGINT AS row_size, sum(q) AS q FROM s WHERE row & 9 = 9 GROUP BY ALL) SELECT j AS row_size, round(coalesce(q, 0) / (SELECT sum(q) FROM c), 9) AS prob FROM range(0, 6) t(j) LEFT JOIN c ON j = row_size")
def size_distribution_given(spark, sf_dir):
    return _sizes(spark, Z.given(Z.size_distribution(_PROBS), [0.5, 0.95]))


@query("recursive_sizes", f"WITH RECURSIVE {_P3}, r(k, d) AS (SELECT 0, [1.0::DOUBLE] UNION ALL SELECT r.k + 1, list_transform(range(0, len(d) + 1), lambda j: coalesce(d[j + 1], 0) * (1 - v) + (CASE WHEN j > 0 THEN d[j] ELSE 0 END) * v) FROM r JOIN p ON p.k = r.k + 1) SELECT unnest(range(0, 6)) AS row_size, unnest(list_transform(d, lambda x: round(x, 9))) AS prob FROM r WHERE k = 5")
def recursive_sizes(spark, sf_dir):
    """The size distribution as a recursive query."""
    spark.createDataFrame(list(enumerate(_PROBS, 1)), "k int, v double").createOrReplaceTempView("quillon_probs")
    return spark.sql("""WITH RECURSIVE r(k, d) AS (SELECT 0, array(1.0D) UNION ALL
        SELECT r.k + 1, transform(sequence(0, size(d)), j -> coalesce(try_element_at(d, j + 1), 0) * (1 - v) + CASE WHEN j > 0 THEN d[j - 1] * v ELSE 0 END) FROM r JOIN quillon_probs p ON p.k = r.k + 1)
        SELECT row_size, round(prob, 9) AS prob FROM r LATERAL VIEW posexplode(d) t AS row_size, prob WHERE k = 5""").select(F.col("row_size").cast("long").alias("row_size"), "prob")


# models of a view's most frequent items

def _base(view: str, m: int) -> str:
    return f"WITH RECURSIVE {masks(view, m)}"


_COL = ", " + fit("c", 9, MARGINS, 2)


def _pair(a: str, b: str) -> str:
    return f"(SELECT sum(1 << id)::BIGINT FROM items WHERE item IN ('{a}', '{b}'))"


_SETS = (("click", "h=1"), ("h=2", "view"))
_PAIRS = " UNION ALL ".join(f"SELECT {_pair(a, b)} AS mask, NULL::INT AS size, {support(_pair(a, b))} / n AS fr FROM nn" for a, b in _SETS)
_BOTH = ", " + fit("w", 9, f"{MARGINS} UNION ALL {_PAIRS}", 60)
_LL = "(SELECT sum(cnt * log2({0}.p[bag.mask + 1])) FROM bag, {0})"


def _with_pairs(b: Bag, known: str = "columns") -> MaxEntModel:
    model = background(b, known)
    sets = [b.mask(*s) for s in _SETS]
    got = b.supports_of(sets)
    return MaxEntModel(b.m, sets, [got[x] / b.n for x in sets], model.margins, model.row_sizes).fit(1e-11, 3000)


_EST9 = "SELECT x.item || '|' || y.item AS items, round({0}, 5) AS est FROM {1}, items x, items y WHERE x.item < y.item"


def _pair_estimates(spark, b: Bag, model: MaxEntModel) -> DataFrame:
    return frame(spark, [(b.names(x), round(model.query(x), 5)) for x in small_sets(b.m, 2)], "items string, est double")


@query("fit_with_columns", _base("user_day", 9) + _BOTH + " " + _EST9.format(estimate("w.p", "(1 << x.id) | (1 << y.id)"), "w"))
def fit_with_columns(spark, sf_dir):
    """Estimates of all pairs after two pairs and the item frequencies are known."""
    b = bag(spark, sf_dir, "user_day", 9)
    return _pair_estimates(spark, b, _with_pairs(b))


@query("block_mass_columns", f"WITH {masks('user_day', 9)}, m AS (SELECT {_pair('click', 'h=1')} AS x, {_pair('h=2', 'view')} AS y), pr AS (SELECT id, supp / n AS p FROM items, nn), s AS (SELECT i::BIGINT AS row, product(CASE WHEN (i >> id) & 1 = 1 THEN p ELSE 1 - p END) AS q FROM range(0, 512) t(i), pr GROUP BY i) SELECT (CASE WHEN row & x = x THEN 1 ELSE 0 END + CASE WHEN row & y = y THEN 2 ELSE 0 END)::BIGINT AS block, round(sum(q), 9) AS mass FROM s, m GROUP BY ALL")
def block_mass_columns(spark, sf_dir):
    """Block masses if items are independent with their own frequencies."""
    b = bag(spark, sf_dir, "user_day", 9)
    sets = [b.mask(*s) for s in _SETS]
    found = B.closed_blocks(sets)
    got, _ = B.quick_sizes(sets, found, B.cumulative(found, B.independent_mass(b.margins)))
    return frame(spark, [(k, round(float(v[0]), 9)) for k, v in got.items()], "block long, mass double")


@query("fit_with_rows", _base("user_day", 9) + ", " + fit("w", 9, f"{MARGINS} UNION ALL {row_sizes(9)} UNION ALL {_PAIRS}", 120) + " " + _EST9.format(estimate("w.p", "(1 << x.id) | (1 << y.id)"), "w"))
def fit_with_rows(spark, sf_dir):
    """The same with the distribution of row sizes known, too."""
    b = bag(spark, sf_dir, "user_day", 9)
    return _pair_estimates(spark, b, _with_pairs(b, "rows+columns"))


@query("bg_comparison", _base("user_day", 9) + _COL + ", " + fit("r", 9, f"{MARGINS} UNION ALL {row_sizes(9)}", 60) + f"""
SELECT 'none' AS background, round(9 * n, 2) AS bits, round(9 * n, 2) AS with_cost FROM nn UNION ALL
SELECT 'columns', round(-{_LL.format('c')}, 2), round(-{_LL.format('c')} + 9 * log2(n), 2) FROM nn UNION ALL
SELECT 'rows+columns', round(-{_LL.format('r')}, 2), round(-{_LL.format('r')} + 19 * log2(n), 2) FROM nn""")
def bg_comparison(spark, sf_dir):
    """Negative log-likelihood under each background, and with log n bits for each number that it stores."""
    b = bag(spark, sf_dir, "user_day", 9)
    rows = [(k, -background(b, k).log_likelihood(b.n), c) for k, c in (("none", 0), ("columns", 9), ("rows+columns", 19))]
    return frame(spark, [(k, round(v, 2), round(v + c * math.log2(b.n), 2)) for k, v, c in rows], "background string, bits double, with_cost double")


@query("bg_empty_score", _base("user_day", 9) + " SELECT round(9 * n, 4) AS bic, round(9 * n + 1, 4) AS mdl FROM nn")
def bg_empty_score(spark, sf_dir):
    b = bag(spark, sf_dir, "user_day", 9)
    return frame(spark, [tuple(round(model_score(b, background(b, "none"), k), 4) for k in ("bic", "mdl"))], "bic double, mdl double")


@query("background_score", _base("user_day", 9) + _COL + f" SELECT round(-{_LL.format('c')}, 3) AS bic, round(1 - {_LL.format('c')}, 3) AS mdl")
def background_score(spark, sf_dir):
    """Scores of the empty list; they differ by one bit."""
    b = bag(spark, sf_dir, "user_day", 9)
    return frame(spark, [tuple(round(model_score(b, background(b), k), 3) for k in ("bic", "mdl"))], "bic double, mdl double")


@query("loglik_rows", _base("user_day", 9) + _BOTH + f" SELECT round({_LL.format('w')}, 3) AS bits")
def loglik_rows(spark, sf_dir):
    """Log-likelihood as a sum over the distinct rows."""
    b = bag(spark, sf_dir, "user_day", 9)
    model = _with_pairs(b)
    p = F.lit(1 / model.total())
    has = lambda x: F.col("mask").bitwiseAND(F.lit(x).cast("long")) == x
    for i, q in enumerate(model.probability):
        p = p * F.when(has(1 << i), q).otherwise(1 - q)
    for x, u in zip(model.members, model.mult, strict=True):
        p = p * F.when(has(x), u).otherwise(1.0)
    return b.rows.agg(F.round(F.sum(F.col("cnt") * F.log2(p)), 3).alias("bits"))


@query("loglik_params", SQL["loglik_rows"])
def loglik_params(spark, sf_dir):
    """The same from the parameters and frequencies, without the rows."""
    b = bag(spark, sf_dir, "user_day", 9)
    return frame(spark, [(round(_with_pairs(b).log_likelihood(b.n), 3),)], "bits double")


_MDL = "log2(n) + 9 * log2(1 + 1 / 9::DOUBLE) + 1"


@query("score_bic", _base("user_day", 9) + _BOTH + f" SELECT round(-{_LL.format('w')} + log2(n), 3) AS score FROM nn")
def score_bic(spark, sf_dir):
    b = bag(spark, sf_dir, "user_day", 9)
    return frame(spark, [(round(model_score(b, _with_pairs(b), "bic"), 3),)], "score double")


@query("score_mdl", _base("user_day", 9) + _BOTH + f" SELECT round(-{_LL.format('w')} + 2 * ({_MDL}) + 4 * log2(9) + 1, 3) AS score FROM nn")
def score_mdl(spark, sf_dir):
    b = bag(spark, sf_dir, "user_day", 9)
    return frame(spark, [(round(model_score(b, _with_pairs(b), "mdl"), 3),)], "score double")


@query("score_drop", _base("user_day", 9) + _BOTH + _COL + f" SELECT round({_LL.format('w')} - {_LL.format('c')} - 2 * ({_MDL}) - 4 * log2(9), 3) AS bits FROM nn")
def score_drop(spark, sf_dir):
    """What two given pairs take off the score; negative if they don't pay."""
    b = bag(spark, sf_dir, "user_day", 9)
    return frame(spark, [(round(model_score(b, background(b), "mdl") - model_score(b, _with_pairs(b), "mdl"), 3),)], "bits double")


@query("data_divergence", _base("user_day", 9) + _BOTH + f" SELECT round(-{_LL.format('w')} / n + (SELECT sum(cnt / n * log2(cnt / n)) FROM bag, nn), 6) AS bits FROM nn")
def data_divergence(spark, sf_dir):
    """Divergence of the data's own distribution from the model's."""
    b = bag(spark, sf_dir, "user_day", 9)
    h = b.rows.agg(-F.sum(F.col("cnt") / b.n * F.log2(F.col("cnt") / b.n))).first()[0]
    return frame(spark, [(round(-_with_pairs(b).log_likelihood(b.n) / b.n - h, 6),)], "bits double")


@query("mdl_l1_gap", "SELECT n::BIGINT AS n, round(log2(n) + 50 * log2(1 + 1 / 50::DOUBLE) + 1, 5) AS exact, round(log2(n) + log2(exp(1)) + 1, 5) AS near FROM (VALUES (6000), (15000), (60000)) t(n)")
def mdl_l1_gap(spark, sf_dir):
    return frame(spark, [(n, round(scores.set_bits(n, 50), 5), round(scores.set_bits(n, 50, True), 5)) for n in (6000, 15000, 60000)], "n long, exact double, near double")


@query("best_itemset", _base("user_day", 9) + f""", s AS (SELECT i::BIGINT AS x FROM range(0, 512) t(i) WHERE bit_count(i::BIGINT) BETWEEN 2 AND 4), e AS (SELECT x, {support('s.x')} / n AS fr, (SELECT product(supp / n) FROM items, nn WHERE (x >> id) & 1 = 1) AS est, n FROM s, nn),
h AS (SELECT x, {kl('fr', 'est')} - bit_count(x) * log2(9) / n AS h FROM e WHERE fr > 0) SELECT {name_of('x')} AS items, round(h, 9) AS h FROM h ORDER BY round(h, 12) DESC LIMIT 1""")
def best_itemset(spark, sf_dir):
    """The most surprising itemset of two to four items, by branch and bound."""
    b = bag(spark, sf_dir, "user_day", 9)
    x, _, h = find_best(b, background(b), "mdl", 10, 4, 1, {})
    return frame(spark, [(b.names(x), round(h, 9))], "items string, h double")


@query("best_specialization", _base("user_day", 9) + f""", root AS (SELECT {_pair('click', 'h=1')} AS r), e AS (SELECT (r | (1 << id))::BIGINT AS x, {support('(r | (1 << id))')} / n AS fr, n FROM root, items, nn WHERE (r >> id) & 1 = 0),
h AS (SELECT x, {kl('fr', 'est')} - 3 * log2(9) / n AS h FROM (SELECT *, (SELECT product(supp / n) FROM items, nn WHERE (x >> id) & 1 = 1) AS est FROM e)) SELECT {name_of('x')} AS items, round(h, 9) AS h FROM h ORDER BY round(h, 12) DESC LIMIT 1""")
def best_specialization(spark, sf_dir):
    """The most surprising itemset with one more item than a given one."""
    b = bag(spark, sf_dir, "user_day", 9)
    x, _, h = Session(b, max_size=3).specialize(b.mask("click", "h=1"))
    return frame(spark, [(b.names(x), round(h, 9))], "items string, h double")


@query("exact_greedy_pairs", _base("user_day", 9) + ", g AS (SELECT x.item AS a, y.item AS b, x.supp / n AS fa, y.supp / n AS fb, " + support("(1 << x.id) | (1 << y.id)") + " / n AS fr FROM items x, items y, nn WHERE x.item < y.item), v AS (SELECT a, b, " + " + ".join(f"(CASE WHEN {q} <= 0 THEN 0 ELSE {q} * log2({q} / ({e})) END)" for q, e in (("fr", "fa * fb"), ("(fa - fr)", "fa * (1 - fb)"), ("(fb - fr)", "(1 - fa) * fb"), ("(1 - fa - fb + fr)", "(1 - fa) * (1 - fb)"))) + " AS gain FROM g) SELECT a || '|' || b AS items, round(gain, 6) AS gain FROM v ORDER BY gain DESC LIMIT 1")
def exact_greedy_pairs(spark, sf_dir):
    """The pair with the largest exact gain, by refitting with every pair."""
    b = bag(spark, sf_dir, "user_day", 9)
    pool = {x: s / b.n for x, s in b.supports_of(small_sets(9, 2)).items() if s}
    base = background(b)
    x, _, _ = best_by_gain(b, base, pool, "bic", 10)
    gain = (model_score(b, base, "bic") - model_score(b, base.with_set(x, pool[x]), "bic") + math.log2(b.n) / 2) / b.n
    return frame(spark, [(b.names(x), round(gain, 6))], "items string, gain double")


@query("lazy_equals_cached")
def lazy_equals_cached(spark, sf_dir):
    b = bag(spark, sf_dir, "user_day", 9)
    lazy, cached = (summarize(b, "mdl", k=2, max_size=3, supports=s) for s in ("lazy", "cached"))
    return frame(spark, [([b.names(p.items) for p in lazy.picks] == [b.names(p.items) for p in cached.picks], lazy.nodes, lazy.pruned, lazy.counted, cached.counted)], "equal boolean, nodes long, pruned long, counted_lazy long, counted_cached long")


@query("exhaustive_vs_greedy")
def exhaustive_vs_greedy(spark, sf_dir):
    """The greedy list beside the best of all subsets of a pool of seven pairs."""
    b = bag(spark, sf_dir, "user_day", 9)
    base = background(b)
    counts = b.supports_of(small_sets(9, 2))
    top = sorted(counts, key=lambda x: -scores.kl2_value(counts[x] / b.n, base.query(x)))[:7]
    best, chosen = optimal_subset(b, {x: counts[x] / b.n for x in top}, "bic")
    greedy = summarize(b, "bic", k=7, pool={x: counts[x] for x in top})
    return frame(spark, [(round(best, 3), len(chosen), round(greedy.score, 3), len(greedy.picks))], "best double, best_k int, greedy double, greedy_k int")


@query("warm_vs_cold_fit")
def warm_vs_cold_fit(spark, sf_dir):
    b = bag(spark, sf_dir, "user_day", 9)
    model = _with_pairs(b)
    x = b.mask("error", "h=0")
    fr = b.supports_of([x])[x] / b.n
    warm = model.with_set(x, fr)
    cold = MaxEntModel(b.m, [*model.members, x], [*model.frequencies, fr], model.margins).fit()
    return frame(spark, [(warm.sweeps, cold.sweeps, round(abs(warm.log_likelihood(b.n) - cold.log_likelihood(b.n)), 4))], "warm_sweeps int, cold_sweeps int, difference double")


@query("interactive_replay")
def interactive_replay(spark, sf_dir):
    """A session: two extensions, a removal, an addition."""
    b = bag(spark, sf_dir, "user_day", 9)
    s = Session(b, max_size=2)
    out = [("start", "", round(s.score(), 1))]
    for x in s.extend(2):
        out.append(("extend", b.names(x), round(s.score(), 1)))
    first = s.model.members[0]
    out.append(("remove", b.names(first), round(s.remove(first), 1)))
    out.append(("add", b.names(first), round(s.add(first), 1)))
    return frame(spark, out, "step string, items string, score double")


@query("run_stats")
def run_stats(spark, sf_dir):
    s = summarize(bag(spark, sf_dir, "user_day", 9), "mdl", k=3, max_size=3, supports="lazy")
    return frame(spark, [("user_day", "mdl", len(s.picks), s.sweeps, s.nodes, s.pruned, s.counted)], "view string, score string, k int, sweeps int, nodes long, pruned long, counted long")


@query("item_partition")
def item_partition(spark, sf_dir):
    """Items put into parts by merging those whose union describes the rows in fewer bits, while any does."""
    b = wide_bag_of(transactions(spark, sf_dir, "order_attr"))
    parts, bits = partition_items(b)
    return frame(spark, [(b.names(1 << i), k, round(bits, 2)) for k, p in enumerate(parts) for i in range(b.m) if p >> i & 1], "item string, part int, bits double")


