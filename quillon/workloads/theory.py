"""Redundancy, invariants of model and scores, and operators around them, with SQL that recomputes each number."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import scores
from ..functions.scores import kl2
from ..operators import blocks as B
from ..operators.bag import margins
from ..operators.pool import Part, free_rows
from ..operators.swap import swap_randomize
from ..operators.vertical import mine, vertical
from ..sources.files import shared_folder, stored
from ..sources.views import table, transactions
from .modelling import _BOTH, _COL, _LL, _PAIRS, _POOL, _base, _pair, _with_pairs, background, bag, frame, frequent_pairs, model_score
from .ranking import _ranked, ranked_pairs
from .sqlparts import MARGINS, cells, estimate, fit, kl, masks, name_of, support

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


# redundancy among all itemsets of part_attr with three rows or more; its rows have five items, so no level is missing

_LEVELS = f"""WITH {cells('part_attr')}, rowsets AS (SELECT tid, list(item ORDER BY item) AS items FROM cells GROUP BY tid),
s AS (SELECT items, count(*) AS supp FROM (SELECT list_filter(items, lambda x, i: (m >> (i - 1)) & 1 = 1) AS items FROM (SELECT items, unnest(range(1, 1 << len(items))) AS m FROM rowsets)) GROUP BY items HAVING count(*) >= 3),
f AS MATERIALIZED (SELECT items, array_to_string(items, '|') AS key, len(items) AS size, supp FROM s),
up AS MATERIALIZED (SELECT array_to_string(list_filter(items, lambda x: x <> drop), '|') AS key, key AS bigger, supp AS bigger_supp FROM (SELECT *, unnest(items) AS drop FROM f) WHERE size > 1)"""


def _levels(spark, sf_dir) -> DataFrame:
    """(key, size, supp, items): all itemsets of any size that three parts have."""
    rows = transactions(spark, sf_dir, "part_attr").select("items")
    v = vertical(rows, 3)
    names = F.array(*map(F.lit, v.items))
    named = F.array_sort(F.transform("items", lambda i: F.element_at(names, i + 1)))
    many = mine(v).select(named.alias("items"), "supp")
    one = spark.createDataFrame([([x], int(s)) for x, s in zip(v.items, v.supports, strict=True)], "items array<string>, supp long")
    return stored(many.union(one).select(F.concat_ws("|", "items").alias("key"), F.size("items").alias("size"), "supp", "items"), "levels")


def _next(levels: DataFrame) -> DataFrame:
    """(key, bigger, bigger_supp): each itemset and those with one item more, by an equi-join on what is left without it."""
    return levels.where("size > 1").select(F.explode(F.transform("items", lambda x: F.concat_ws("|", F.array_remove("items", x)))).alias("key"), F.col("key").alias("bigger"), F.col("supp").alias("bigger_supp"))


def condensed(levels: DataFrame) -> DataFrame:
    """`levels` with flags: closed (no superset has its support), generator (no subset has)."""
    pairs = levels.join(_next(levels), "key")
    wide = pairs.where("bigger_supp = supp").select("key").distinct().withColumn("wider", F.lit(True))
    tight = pairs.where("bigger_supp = supp").select(F.col("bigger").alias("key")).distinct().withColumn("tighter", F.lit(True))
    out = levels.join(wide, "key", "left").join(tight, "key", "left")
    return out.select("key", "size", "supp", F.col("wider").isNull().alias("closed"), F.col("tighter").isNull().alias("generator"))


@query("closed_itemsets", _LEVELS + " SELECT key, supp FROM f WHERE key NOT IN (SELECT key FROM up JOIN f USING (key) WHERE bigger_supp = supp)")
def closed_itemsets(spark, sf_dir):
    return condensed(_levels(spark, sf_dir)).where("closed").select("key", "supp")


@query("generator_itemsets", _LEVELS + " SELECT key, supp FROM f WHERE key NOT IN (SELECT bigger FROM up JOIN f USING (key) WHERE bigger_supp = supp)")
def generator_itemsets(spark, sf_dir):
    return condensed(_levels(spark, sf_dir)).where("generator").select("key", "supp")


@query("between_closure_redundant", _LEVELS + " SELECT z.key, z.supp FROM f z WHERE EXISTS (SELECT 1 FROM f y WHERE y.supp = z.supp AND y.size < z.size AND list_has_all(z.items, y.items)) AND EXISTS (SELECT 1 FROM f x WHERE x.supp = z.supp AND x.size > z.size AND list_has_all(x.items, z.items))")
def between_closure_redundant(spark, sf_dir):
    """Itemsets strictly between a generator and its closure, all of one support: known once those two are."""
    return condensed(_levels(spark, sf_dir)).where("NOT closed AND NOT generator").select("key", "supp")


@query("lossy_redundancy", _LEVELS + " SELECT f.key, f.supp, max(bigger_supp) AS nearest FROM f JOIN up ON up.key = f.key GROUP BY ALL HAVING max(bigger_supp) >= 0.8 * f.supp")
def lossy_redundancy(spark, sf_dir):
    """Itemsets whose support a superset nearly has, to within a fifth."""
    levels = _levels(spark, sf_dir)
    nearest = levels.join(_next(levels), "key").groupBy("key", "supp").agg(F.max("bigger_supp").alias("nearest"))
    return nearest.where("nearest >= 0.8 * supp")


@query("condense_pool", _LEVELS + ", c AS (SELECT key FROM f WHERE key NOT IN (SELECT key FROM up JOIN f USING (key) WHERE bigger_supp = supp)), g AS (SELECT key FROM f WHERE key NOT IN (SELECT bigger FROM up JOIN f USING (key) WHERE bigger_supp = supp)) SELECT 'all' AS pool, count(*) AS itemsets FROM f UNION ALL SELECT 'closed', count(*) FROM c UNION ALL SELECT 'generators', count(*) FROM g")
def condense_pool(spark, sf_dir):
    """How far lossless condensation shortens a pool."""
    n = condensed(_levels(spark, sf_dir)).agg(F.count("*").alias("all"), F.count(F.when(F.col("closed"), 1)).alias("closed"), F.count(F.when(F.col("generator"), 1)).alias("generators"))
    return n.select(F.explode(F.create_map(*(x for k in ("all", "closed", "generators") for x in (F.lit(k), F.col(k))))).alias("pool", "itemsets"))


_TRIPLES = _LEVELS + """, t AS (SELECT f.key, f.supp, f.items[1] AS a, f.items[2] AS b, f.items[3] AS c FROM f WHERE size = 3), w AS (SELECT key, supp FROM f),
b3 AS (SELECT t.key, t.supp, x.supp AS sa, y.supp AS sb, z.supp AS sc, p.supp AS sab, q.supp AS sac, r.supp AS sbc, n::BIGINT AS n FROM t JOIN w x ON x.key = a JOIN w y ON y.key = b JOIN w z ON z.key = c JOIN w p ON p.key = a || '|' || b JOIN w q ON q.key = a || '|' || c JOIN w r ON r.key = b || '|' || c, nn)
SELECT key, supp, greatest(0, sab + sac - sa, sab + sbc - sb, sac + sbc - sc) AS lower, least(sab, sac, sbc, sab + sac + sbc - sa - sb - sc + n) AS upper, greatest(0, sab + sac - sa, sab + sbc - sb, sac + sbc - sc) = least(sab, sac, sbc, sab + sac + sbc - sa - sb - sc + n) AS derivable FROM b3"""


@query("derivable_itemsets", _TRIPLES)
def derivable_itemsets(spark, sf_dir):
    """Bounds on triples' supports from all their subsets by inclusion and exclusion; equal bounds make one derivable."""
    levels = _levels(spark, sf_dir)
    n = transactions(spark, sf_dir, "part_attr").count()
    out = levels.where("size = 3").select("key", "supp", "items")
    for name, places in (("a", (1,)), ("b", (2,)), ("c", (3,)), ("ab", (1, 2)), ("ac", (1, 3)), ("bc", (2, 3))):
        part = F.concat_ws("|", *(F.element_at("items", p) for p in places))
        out = out.withColumn("part", part).join(levels.select(F.col("key").alias("part"), F.col("supp").alias(name)), "part").drop("part")
    lower = F.greatest(F.lit(0), F.expr("ab + ac - a"), F.expr("ab + bc - b"), F.expr("ac + bc - c"))
    upper = F.least("ab", "ac", "bc", F.expr(f"ab + ac + bc - a - b - c + {n}"))
    return out.select("key", "supp", lower.alias("lower"), upper.alias("upper"), (lower == upper).alias("derivable"))


# invariants, both sides computed

_SAME = ", " + fit("w2", 9, f"{MARGINS} UNION ALL {_PAIRS} UNION ALL SELECT x, NULL::INT, {estimate('w.p', 'k.x')} FROM w, (SELECT {_pair('click', 'h=2')} AS x) k", 60)
_SET_COST = "log2(n) + 9 * log2(1 + 1 / 9::DOUBLE) + 1 + 2 * log2(9)"


@query("redundant_candidate", _base("user_day", 9) + _BOTH + _SAME + f", l AS (SELECT {_LL.format('w')} AS a, {_LL.format('w2')} AS b, n FROM nn) SELECT 'bic' AS score, round(-a + log2(n), 2) AS without, round(-b + 1.5 * log2(n), 2) AS with_it, -b + 1.5 * log2(n) > -a + log2(n) AS worse FROM l UNION ALL SELECT 'mdl', round(-a + 2 * ({_SET_COST}) + 1, 2), round(-b + 3 * ({_SET_COST}) + 1, 2), -b + ({_SET_COST}) > -a FROM l")
def redundant_candidate(spark, sf_dir):
    """An itemset at exactly its estimate makes both scores worse."""
    b = bag(spark, sf_dir, "user_day", 9)
    model = _with_pairs(b)
    x = b.mask("click", "h=2")
    more = model.with_set(x, model.query(x))
    both = [(k, model_score(b, model, k), model_score(b, more, k)) for k in ("bic", "mdl")]
    return frame(spark, [(k, round(v, 2), round(w, 2), w > v) for k, v, w in both], "score string, without double, with_it double, worse boolean")


_SHIFTED = "".join(", " + fit(f"g{k}", 9, f"{MARGINS} UNION ALL SELECT {_pair('click', 'h=1')}, NULL::INT, {support(_pair('click', 'h=1'))} / n + ({d}) FROM nn", 60) for k, d in enumerate((-0.02, 0.0, 0.02)))


@query("consistency_maximizes", _base("user_day", 9) + _SHIFTED + ", v AS (" + " UNION ALL ".join(f"SELECT {d}::DOUBLE AS delta, {_LL.format(f'g{k}')} AS bits" for k, d in enumerate((-0.02, 0.0, 0.02))) + ") SELECT delta, round(bits, 2) AS bits, bits = max(bits) OVER () AS best FROM v")
def consistency_maximizes(spark, sf_dir):
    """The likelihood of the data is largest at the data's own frequency."""
    b = bag(spark, sf_dir, "user_day", 9)
    x = b.mask("click", "h=1")
    fr, base = b.supports_of([x])[x] / b.n, background(b)
    value = {}
    for d in (-0.02, 0.0, 0.02):
        model = base.with_set(x, fr + d)
        own = sum(f * math.log2(p) + (1 - f) * math.log2(1 - p) for f, p in zip(b.margins, model.probability, strict=True))
        value[d] = b.n * (-math.log2(model.total()) + fr * math.log2(model.mult[0]) + own)
    return frame(spark, [(d, round(v, 2), v == max(value.values())) for d, v in value.items()], "delta double, bits double, best boolean")


_STATED = (("click", "h=1", None), ("h=2", "view", 0.9), ("error", "h=0", 0.05))


@query("consistency_check", f"WITH {cells('user_day')}, s(a, b, stated) AS (VALUES ('click', 'h=1', NULL::DOUBLE), ('h=2', 'view', 0.9), ('error', 'h=0', 0.05)), c AS (SELECT s.*, (SELECT count(*) FROM cells x JOIN cells y ON x.tid = y.tid WHERE x.item = s.a AND y.item = s.b) / n AS fr, x.supp / n AS fa, y.supp / n AS fb FROM s JOIN margin x ON x.item = s.a JOIN margin y ON y.item = s.b, nn) SELECT a || '|' || b AS items, abs(fr - coalesce(stated, fr)) < 1e-12 AS consistent, coalesce(stated, fr) BETWEEN greatest(0, fa + fb - 1) AND least(fa, fb) AS feasible FROM c")
def consistency_check(spark, sf_dir):
    """Whether stated frequencies are the data's, and whether any data with these margins can have them: there the fit closes in."""
    b = bag(spark, sf_dir, "user_day", 9)
    out = []
    for x, y, stated in _STATED:
        mask = b.mask(x, y)
        fr = b.supports_of([mask])[mask] / b.n
        value = fr if stated is None else stated
        ids = sorted((b.items.index(x), b.items.index(y)))
        part = Part(tuple(ids), [(3, value, True)]).fit(np.array(b.margins), free_rows([b.margins[i] for i in ids]), 1e-9, 5000)
        met = abs(part.within[3] - value) < 1e-4 and all(abs(part.within[1 << k] - b.margins[i]) < 1e-4 for k, i in enumerate(ids))
        out.append((f"{x}|{y}", abs(fr - value) < 1e-12, bool(met)))
    return frame(spark, out, "items string, consistent boolean, feasible boolean")


@query("cap_admissible", f"WITH RECURSIVE {masks('user_day', 9)}, {_POOL}, m AS (SELECT k, x AS mask FROM mem), q AS (SELECT {name_of('x')} AS items, x, cap FROM pool, (VALUES (3), (4), (5)) c(cap) WHERE k BETWEEN 3 AND 11), g AS (SELECT k, k AS other FROM m UNION SELECT g.k, m.k FROM g JOIN m x ON x.k = g.other JOIN m ON m.mask & x.mask <> 0), parts AS (SELECT k, (SELECT bit_or(mask) FROM m WHERE m.k IN (SELECT other FROM g g2 WHERE g2.k = g1.k)) AS all_items FROM (SELECT DISTINCT k FROM g) g1) SELECT items, cap, bit_count((x | coalesce((SELECT bit_or(all_items) FROM parts WHERE all_items & x <> 0), 0))::BIGINT) <= cap AS ok FROM q")
def cap_admissible(spark, sf_dir):
    """Whether the next frequent pairs and the parts of the first three that they touch stay within a cap of items."""
    b = bag(spark, sf_dir, "user_day", 9)
    sets = [x for x, _ in frequent_pairs(b)]
    return frame(spark, [(b.names(x), c, B.admissible(sets[:3], x, c)) for x in sets[3:12] for c in (3, 4, 5)], "items string, cap int, ok boolean")


@query("mdl_prior_mass", "WITH RECURSIVE b AS (SELECT 0 AS x, 1.0::DOUBLE AS v UNION ALL SELECT x + 1, v * (50 - x) / (x + 1) / 50 FROM b WHERE x < 50), one AS (SELECT sum(v) * pow(1 + 1 / 50::DOUBLE, -50) / 2 AS mass FROM b) SELECT k, round(sum(pow(mass, k) / 2) OVER (ORDER BY k), 9) AS mass FROM range(0, 11) t(k), one")
def mdl_prior_mass(spark, sf_dir):
    """Prior mass of all lists of up to k itemsets of 50 items: each itemset summed over its sizes, items and supports."""
    n, m = 1000, 50
    l1, l2 = scores.set_bits(n, m), math.log2(m)
    one = sum(n * math.comb(m, x) * 2.0 ** -(l1 + l2 * x) for x in range(m + 1))
    total, out = 0.0, []
    for k in range(11):
        total += 0.5 * one**k
        out.append((k, round(total, 9)))
    return frame(spark, out, "k long, mass double")


@query("space_size", f"WITH RECURSIVE {cells('user_day')}, s AS (SELECT x.item AS a, y.item AS b FROM cells x JOIN cells y ON x.tid = y.tid AND x.item < y.item GROUP BY ALL HAVING count(*) >= 200), f AS (SELECT (SELECT count(*) FROM s) AS n), c AS (SELECT 0 AS j, 1::DOUBLE AS v, 1::DOUBLE AS total UNION ALL SELECT j + 1, v * (n - j) / (j + 1), total + v * (n - j) / (j + 1) FROM c, f WHERE j < 4) SELECT j, round(v)::BIGINT AS lists, round(total)::BIGINT AS lists_up_to FROM c")
def space_size(spark, sf_dir):
    """How many lists of j pairs a pool allows, and of up to j."""
    rows = transactions(spark, sf_dir, "user_day")
    n = mine(vertical(rows, 200), 2).count()
    return frame(spark, [(j, math.comb(n, j), sum(math.comb(n, i) for i in range(j + 1))) for j in range(5)], "j int, lists long, lists_up_to long")


@query("one_step_divergence", _base("user_day", 9) + _COL + f" SELECT x.item || '|' || y.item AS items, round({kl('fr', 'est')}, 6) AS bits FROM (SELECT x, y, {support('(1 << x.id) | (1 << y.id)')} / n AS fr, {estimate('c.p', '(1 << x.id) | (1 << y.id)')} AS est FROM items x, items y, c, nn WHERE x.item < y.item)")
def one_step_divergence(spark, sf_dir):
    """Divergence, summed over all rows, of the model after one single update by a pair: its one-term surprise."""
    b = bag(spark, sf_dir, "user_day", 9)
    old, kinds, out = free_rows(b.margins), np.arange(1 << 9), []
    pairs = [(1 << i) | (1 << j) for i in range(9) for j in range(i)]
    for x, s in b.supports_of(pairs).items():
        inside, fr = (kinds & x) == x, s / b.n
        est = old[inside].sum()
        new = np.where(inside, old * fr / est, old * (1 - fr) / (1 - est))
        some = new > 0
        out.append((b.names(x), round(float((new[some] * np.log2(new[some] / old[some])).sum()), 6)))
    return frame(spark, out, "items string, bits double")


@query("same_frequencies_same_model", _base("user_day", 9) + _COL + f" SELECT s AS data, round({estimate('c.p', 'k.x')}, 9) AS est, round(-{_LL.format('c')}, 3) AS bits FROM c, (SELECT {_pair('click', 'h=1')} AS x) k, (VALUES ('own'), ('randomised')) t(s)")
def same_frequencies_same_model(spark, sf_dir):
    """The data and a version with the same item frequencies, but other rows: one model, and one likelihood of the data."""
    rows = transactions(spark, sf_dir, "user_day")
    out = []
    for name, own in (("own", rows), ("randomised", swap_randomize(rows, 1).select("tid", "items"))):
        v = vertical(own, 1)
        at = {x: k for k, x in enumerate(v.items)}
        bits = v.n * sum(-f * math.log2(f) - (1 - f) * math.log2(1 - f) for f in v.frequencies if 0 < f < 1)
        out.append((name, round(float(v.frequencies[at["click"]] * v.frequencies[at["h=1"]]), 9), round(float(bits), 3)))
    return frame(spark, out, "data string, est double, bits double")


_EPS = 0.01
_SMOOTH = f"SELECT 1 << id AS mask, NULL::INT AS size, {1 - _EPS} * supp / n + {_EPS} * 0.5 AS fr FROM items, nn"


@query("fit_smoothed", _base("user_day", 9) + ", " + fit("z", 9, f"{_SMOOTH} UNION ALL SELECT mask, size, {1 - _EPS} * fr + {_EPS} * 0.25 FROM ({_PAIRS})", 80) + f" SELECT x.item || '|' || y.item AS items, round({estimate('z.p', '(1 << x.id) | (1 << y.id)')}, 5) AS est FROM z, items x, items y WHERE x.item < y.item")
def fit_smoothed(spark, sf_dir):
    """Estimates when all frequencies, of items and of itemsets, are mixed with those of rows drawn evenly."""
    b = bag(spark, sf_dir, "user_day", 9)
    sets = [b.mask("click", "h=1"), b.mask("h=2", "view")]
    got = b.supports_of(sets)
    margins_ = np.array([(1 - _EPS) * f + _EPS * 0.5 for f in b.margins])
    part = Part(tuple(range(9)), [(x, (1 - _EPS) * got[x] / b.n + _EPS * 0.25, True) for x in sets]).fit(margins_, free_rows(margins_), 1e-10, 3000)
    return frame(spark, [(b.names((1 << i) | (1 << j)), round(float(part.within[(1 << i) | (1 << j)]), 5)) for i in range(9) for j in range(i)], "items string, est double")


# operators around the methods

@query("attribute_items", f"WITH {cells('part_attr')} SELECT split_part(item, '=', 1) AS attribute, split_part(item, '=', 2) AS value, supp FROM margin")
def attribute_items(spark, sf_dir):
    """Attribute=value items of a table, counted, taken apart again."""
    rows = transactions(spark, sf_dir, "part_attr").select(F.explode("items").alias("item"))
    return rows.groupBy(F.split_part("item", F.lit("="), F.lit(1)).alias("attribute"), F.split_part("item", F.lit("="), F.lit(2)).alias("value")).agg(F.count("*").alias("supp"))


@query("item_filter", f"WITH {cells('order_attr')} SELECT item, supp FROM margin WHERE item LIKE 'n=%' AND supp BETWEEN 100 AND 100000 AND item NOT IN ('n=NATION_1', 'n=NATION_2') AND item IS NOT NULL")
def item_filter(spark, sf_dir):
    """Items by pattern, support range and deny list."""
    m = transactions(spark, sf_dir, "order_attr").select(F.explode("items").alias("item")).where(F.col("item").like("n=%") & ~F.col("item").isin("n=NATION_1", "n=NATION_2"))
    return m.groupBy("item").agg(F.count("*").alias("supp")).where(F.col("supp").between(100, 100000))


@query("math_kl", f"WITH {cells('user_day')}, v AS (SELECT supp / n AS v FROM margin, nn) SELECT x, y, round({kl('x', 'y')}, 9) AS bits, round(pow(2, -{kl('x', 'y')}), 9) AS odds, round(greatest(x, y) - least(x, y), 9) AS gap, round(exp(ln(x) + ln(y)), 9) AS both FROM (SELECT v AS x FROM v), (SELECT v AS y FROM v)")
def math_kl(spark, sf_dir):
    """The mathematics of the scores on the frequencies of all two items of a view."""
    x, y = F.col("x"), F.col("y")
    rows = transactions(spark, sf_dir, "user_day")
    n = rows.count()
    values = margins(rows).select((F.col("supp") / n).alias("x"))
    grid = values.crossJoin(values.withColumnRenamed("x", "y"))
    return grid.select("x", "y", F.round(kl2(x, y), 9).alias("bits"), F.round(F.pow(F.lit(2.0), -kl2(x, y)), 9).alias("odds"), F.round(F.greatest(x, y) - F.least(x, y), 9).alias("gap"), F.round(F.exp(F.log(x) + F.log(y)), 9).alias("both"))


@query("map_lookup", f"WITH {cells('user_day')}, d AS (SELECT item, row_number() OVER (ORDER BY supp DESC, item) - 1 AS id FROM margin) SELECT tid, array_to_string(list(id ORDER BY id), ',') AS ids, count(*) FILTER (id < 3) AS common FROM cells JOIN d USING (item) GROUP BY tid")
def map_lookup(spark, sf_dir):
    """Rows encoded by a dictionary that is a map, and how many of their items are among its three most frequent."""
    rows = transactions(spark, sf_dir, "user_day")
    order = F.array_sort(F.collect_list(F.struct((-F.col("supp")).alias("s"), "item")))
    counts = rows.select(F.explode("items").alias("item")).groupBy("item").agg(F.count("*").alias("supp"))
    words = counts.agg(F.map_from_entries(F.transform(order, lambda e, i: F.struct(e["item"], i))).alias("ids"))  # one row, one entry an item
    common = F.map_keys(F.map_filter("ids", lambda _, v: v < 3))
    coded = F.array_sort(F.transform("items", lambda x: F.element_at("ids", x)))
    return rows.where(F.size("items") > 0).join(F.broadcast(words)).select("tid", F.concat_ws(",", F.transform(coded, lambda v: v.cast("string"))).alias("ids"), F.size(F.array_intersect("items", common)).cast("long").alias("common"))


_BITS = (("click", "h=1"), ("h=2", "view"), ("error", "h=0"))


@query("bit_signature", f"WITH {cells('user_day')}, s AS (SELECT rws.tid, " + " | ".join(f"((coalesce(bool_or(item = '{a}'), false) AND coalesce(bool_or(item = '{b}'), false))::BIGINT << {k})" for k, (a, b) in enumerate(_BITS)) + " AS sig FROM rws LEFT JOIN cells ON rws.tid = cells.tid GROUP BY rws.tid) SELECT sig, bit_count(sig)::INT AS members, count(*) AS n FROM s GROUP BY ALL")
def bit_signature(spark, sf_dir):
    """Rows by the bits of the itemsets they contain."""
    bits = [F.shiftleft((F.array_contains("items", a) & F.array_contains("items", b)).cast("long"), k) for k, (a, b) in enumerate(_BITS)]
    sig = bits[0].bitwiseOR(bits[1]).bitwiseOR(bits[2]).alias("sig")
    return transactions(spark, sf_dir, "user_day").select(sig).groupBy("sig").agg(F.count("*").alias("n")).select("sig", F.bit_count("sig").alias("members"), "n")


@query("equal_width_items", "WITH w AS (SELECT min(l_extendedprice) AS lo, max(l_extendedprice) AS hi FROM lineitem) SELECT least(10, floor((l_extendedprice - lo) / (hi - lo) * 10) + 1)::BIGINT AS bin, count(*) AS supp FROM lineitem, w GROUP BY ALL")
def equal_width_items(spark, sf_dir):
    """A numeric column as items of ten bins of equal width."""
    t = table(spark, sf_dir, "lineitem").select(F.col("l_extendedprice").alias("v"))
    ends = t.agg(F.min("v").alias("lo"), F.max("v").alias("hi"))
    return t.join(F.broadcast(ends)).groupBy(F.least(F.lit(10), F.floor((F.col("v") - F.col("lo")) / (F.col("hi") - F.col("lo")) * 10) + 1).cast("long").alias("bin")).agg(F.count("*").alias("supp"))


@query("kmeans_items")
def kmeans_items(spark, sf_dir):
    """A numeric column as items of ten clusters, in the order of their centres."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.feature import VectorAssembler

    t = VectorAssembler(inputCols=["p_retailprice"], outputCol="v").transform(table(spark, sf_dir, "part").select("p_retailprice"))
    model = KMeans(k=10, featuresCol="v", seed=7).fit(t)
    order = np.argsort([c[0] for c in model.clusterCenters()])
    rank = F.array(*(F.lit(int(np.where(order == k)[0][0])) for k in range(len(order))))
    return model.transform(t).groupBy(F.element_at(rank, F.col("prediction") + 1).alias("bin")).agg(F.count("*").alias("supp"), F.min("p_retailprice").alias("low"), F.max("p_retailprice").alias("high"))


@query("unselected_candidates", _ranked("user_day") + ", s AS (SELECT a, b FROM k ORDER BY round(h, 12) DESC, a, b LIMIT 5) SELECT k.a, k.b, k.supp FROM k ANTI JOIN s ON k.a = s.a AND k.b = s.b")
def unselected_candidates(spark, sf_dir):
    """Pairs that are not among the five most surprising."""
    r = stored(ranked_pairs(transactions(spark, sf_dir, "user_day")), "ranked")
    top = r.orderBy(F.desc(F.round("h", 12)), "a", "b").limit(5).select("a", "b")
    return r.join(F.broadcast(top), ["a", "b"], "left_anti").select("a", "b", "supp")


@query("score_drop_running", _ranked("user_day") + ", t AS (SELECT a, b, round(n * kl, 6) AS bits FROM k ORDER BY bits DESC, a, b LIMIT 12) SELECT a, b, bits, row_number() OVER w AS rank, round(sum(bits) OVER (w ROWS UNBOUNDED PRECEDING), 5) AS total, round(bits - lag(bits) OVER w, 5) AS step, first_value(bits) OVER w AS best FROM t WINDOW w AS (ORDER BY bits DESC, a, b)")
def score_drop_running(spark, sf_dir):
    """A ranked list with running totals, steps between neighbours and the best; twelve rows, so one window."""
    r = ranked_pairs(transactions(spark, sf_dir, "user_day")).select("a", "b", F.round(F.col("n") * F.col("kl"), 6).alias("bits"))
    top = r.orderBy(F.desc("bits"), "a", "b").limit(12)
    w = Window.orderBy(F.desc("bits"), "a", "b")
    return top.select("a", "b", "bits", F.row_number().over(w).cast("long").alias("rank"), F.round(F.sum("bits").over(w.rowsBetween(Window.unboundedPreceding, 0)), 5).alias("total"), F.round(F.col("bits") - F.lag("bits").over(w), 5).alias("step"), F.first("bits").over(w).alias("best"))


@query("itemset_vs_cluster")
def itemset_vs_cluster(spark, sf_dir):
    """Rows of the most surprising itemset of binned vectors beside k-means clusters: the share of the itemset's rows in each."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    from ..operators.pool import best_of, start_state

    rows = transactions(spark, sf_dir, "emb_bin")
    v = vertical(rows.select("items"), max(1, rows.count() // 50))
    found = best_of(mine(v, 2), start_state(v), "bic")
    inside = F.size(F.array_except(F.array(*(F.lit(v.items[i]) for i in (found[0] if found else ()))), "items")) == 0 if found else F.lit(False)
    named = rows.select(F.col("tid").alias("vec_id"), inside.alias("inside"))
    points = table(spark, sf_dir, "embeddings").select("vec_id", array_to_vector(F.transform("embedding", lambda x: x.cast("double"))).alias("features"))
    clusters = KMeans(k=8, seed=11).fit(points).transform(points).select("vec_id", F.col("prediction").alias("cluster"))
    return clusters.join(named, "vec_id").groupBy("cluster").agg(F.count("*").alias("rows"), F.count(F.when(F.col("inside"), 1)).alias("inside"))


@query("source_formats", f"WITH {cells('part_snation')} SELECT s AS format, item, supp FROM margin, (VALUES ('csv'), ('json'), ('memory')) t(s)")
def source_formats(spark, sf_dir):
    """The same transactions as (tid, item) lines of CSV, as JSON lines and from rows in memory."""
    import uuid

    longs = transactions(spark, sf_dir, "part_snation").select("tid", F.explode("items").alias("item"))
    root, schema = f"{shared_folder(spark)}/formats-{uuid.uuid4().hex}", "tid long, item string"
    longs.write.option("header", True).csv(f"{root}/csv")
    longs.write.json(f"{root}/json")
    memory = spark.createDataFrame(longs.groupBy("item").agg(F.count("*").alias("supp")).toPandas())  # a row an item
    out = memory.select(F.lit("memory").alias("format"), "item", "supp")
    for name, got in (("csv", spark.read.schema(schema).option("header", True).csv(f"{root}/csv")), ("json", spark.read.schema(schema).json(f"{root}/json"))):
        out = out.union(got.groupBy("item").agg(F.count("*").alias("supp")).select(F.lit(name).alias("format"), "item", "supp"))
    return out


# streams

@query("stream_drift", "WITH w AS (SELECT time_bucket(INTERVAL '6 hours', ts, TIMESTAMP '1970-01-01') AS start, event_type, count(*) AS cnt FROM events GROUP BY ALL), t AS (SELECT *, sum(cnt) OVER (PARTITION BY start) AS n FROM w), a AS (SELECT event_type, count(*) / (SELECT count(*) FROM events) AS q FROM events GROUP BY ALL) SELECT start, event_type, round(n * " + kl("(cnt / n)", "q") + ", 6) AS bits FROM t JOIN a USING (event_type)")
def stream_drift(spark, sf_dir):
    """How much each window's event frequencies surprise the overall ones, from margins that a stream keeps."""
    from ..streaming.baskets import event_stream, replayed, window_counts

    w = replayed(window_counts(event_stream(spark, sf_dir, late=None), F.window("ts", "6 hours")), ["start", "event_type"], "cnt")
    w = w.withColumn("n", F.sum("cnt").over(Window.partitionBy("start")))
    e = table(spark, sf_dir, "events")
    n = e.count()
    overall = e.groupBy("event_type").agg((F.count("*") / max(n, 1)).alias("q"))
    return w.join(F.broadcast(overall), "event_type").select("start", "event_type", F.round(F.col("n") * kl2(F.col("cnt") / F.col("n"), F.col("q")), 6).alias("bits"))


def _split_stream(spark: SparkSession, sf_dir: str) -> tuple[str, "StructType"]:
    """The events as three files in order: the first half by time, the second half, and 200 of the first half's once more, late."""
    import uuid

    root = f"{shared_folder(spark)}/late-{uuid.uuid4().hex}"
    e = table(spark, sf_dir, "events")
    middle = e.agg(F.expr("percentile_approx(ts, 0.5)")).first()[0]
    early, late = e.where(F.col("ts") <= middle), e.where(F.col("ts") > middle)
    again = early.orderBy("ts", "event_id").limit(200)
    for part in (early, late, again):
        part.coalesce(1).write.mode("append").parquet(root)
    return root, e.schema


@query("stream_late", "SELECT time_bucket(INTERVAL '6 hours', ts, TIMESTAMP '1970-01-01') AS start, event_type, count(*) AS cnt FROM events GROUP BY ALL")
def stream_late(spark, sf_dir):
    """Window margins of a stream whose last file repeats old events: past the watermark, they don't count again."""
    from ..streaming.baskets import replayed, window_counts

    root, schema = _split_stream(spark, sf_dir)
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(root)
    # watermarks need instants; the table's times have no zone, so they are read as UTC, whatever the session's zone
    stream = stream.withColumn("ts", F.expr("timestamp_micros(timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01 00:00:00', ts))")).withWatermark("ts", "1 hour")
    found = replayed(window_counts(stream, F.window("ts", "6 hours")), ["start", "event_type"], "cnt")
    return found.withColumn("start", F.expr("timestampadd(MICROSECOND, unix_micros(start), TIMESTAMP_NTZ'1970-01-01 00:00:00')"))


@query("stream_dedup", "SELECT event_type, count(DISTINCT event_id) AS cnt FROM events GROUP BY ALL")
def stream_dedup(spark, sf_dir):
    """Event margins of the same stream without a watermark: repeats go by their ids."""
    from ..streaming.baskets import replayed

    root, schema = _split_stream(spark, sf_dir)
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(root).dropDuplicates(["event_id"])
    return replayed(stream.groupBy("event_type").agg(F.count("*").alias("cnt")), ["event_type"], "cnt")


@query("stream_static_join", "WITH k AS (SELECT event_type, row_number() OVER (ORDER BY event_type) AS code FROM (SELECT DISTINCT event_type FROM events)) SELECT code, count(*) AS cnt FROM events JOIN k USING (event_type) GROUP BY ALL")
def stream_static_join(spark, sf_dir):
    """A stream of events encoded by a dictionary table."""
    from ..streaming.baskets import event_stream, replayed

    names = sorted(r["event_type"] for r in table(spark, sf_dir, "events").select("event_type").distinct().collect())  # a row an event type
    words = spark.createDataFrame([(x, k) for k, x in enumerate(names, 1)], "event_type string, code long")
    coded = event_stream(spark, sf_dir, late=None).join(F.broadcast(words), "event_type")
    return replayed(coded.groupBy("code").agg(F.count("*").alias("cnt")), ["code"], "cnt")


@query("stream_user_state", "SELECT user_id, count(DISTINCT event_type) AS kinds, count(*) AS events FROM events GROUP BY ALL")
def stream_user_state(spark, sf_dir):
    """Items seen by each user, kept in a state of its own."""
    import uuid

    import pandas as pd

    root, schema = _split_stream(spark, sf_dir)
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(root).dropDuplicates(["event_id"]).select("user_id", "event_type")

    def seen(key, batches, state):
        kinds, events = state.get if state.exists else ("", 0)
        have = set(filter(None, kinds.split("|")))
        for b in batches:
            have |= set(b["event_type"].dropna())
            events += len(b)
        state.update(("|".join(sorted(have)), events))
        yield pd.DataFrame({"user_id": [key[0]], "kinds": [len(have)], "events": [events]})

    out = stream.groupBy("user_id").applyInPandasWithState(seen, "user_id long, kinds long, events long", "kinds string, events long", "update", "NoTimeout")
    folder = f"{shared_folder(spark)}/state-{uuid.uuid4().hex}"
    running = out.writeStream.outputMode("update").foreachBatch(lambda df, k: df.write.mode("overwrite").parquet(f"{folder}/changes/batch={k}")).option("checkpointLocation", f"{folder}/check").trigger(availableNow=True).start()
    running.awaitTermination()
    return spark.read.parquet(f"{folder}/changes").groupBy("user_id").agg(F.max_by("kinds", "batch").alias("kinds"), F.max_by("events", "batch").alias("events"))

