"""DuckDB SQL pieces: views as cells, and fits by enumeration of all rows, which share no method with the engine."""

from __future__ import annotations

_ORDER_CELLS = "SELECT DISTINCT l_orderkey AS tid, {0} AS item FROM lineitem JOIN part ON l_partkey = p_partkey"
_ATTR = "SELECT DISTINCT tid, item FROM (SELECT tid, unnest([{0}]) AS item FROM ({1})) WHERE item IS NOT NULL"
_BIN = "CASE WHEN embedding[{0}] < CAST(-0.1 AS DOUBLE) THEN 1 WHEN embedding[{0}] < 0 THEN 2 WHEN embedding[{0}] < CAST(0.1 AS DOUBLE) THEN 3 ELSE 4 END"

#: view: (rows with a tid, cells with tid and item)
CELLS: dict[str, tuple[str, str]] = {
    "order_brand": ("SELECT o_orderkey AS tid FROM orders", _ORDER_CELLS.format("p_brand")),
    "order_word": (
        "SELECT o_orderkey AS tid FROM orders",
        "SELECT DISTINCT tid, unnest([p_type, split_part(p_name, ' ', 1), split_part(p_name, ' ', 2)]) AS item FROM (SELECT l_orderkey AS tid, p_type, p_name FROM lineitem JOIN part ON l_partkey = p_partkey)",
    ),
    "part_attr": (
        "SELECT p_partkey AS tid FROM part",
        _ATTR.format("'brand=' || p_brand, 'type=' || p_type, 'n1=' || split_part(p_name, ' ', 1), 'n2=' || split_part(p_name, ' ', 2), 'size=' || ((p_size - 1) // 10)", "SELECT p_partkey AS tid, * FROM part"),
    ),
    "line_attr": (
        "SELECT row_number() OVER () AS tid FROM lineitem",
        _ATTR.format("'rf=' || l_returnflag, 'ls=' || l_linestatus, 'disc=' || CAST(round(l_discount * 100) AS INT), 'tax=' || CAST(round(l_tax * 100) AS INT), 'ln=' || l_linenumber, 'q=' || CAST(floor((l_quantity - 1) / 10) AS INT)", "SELECT row_number() OVER () AS tid, * FROM lineitem"),
    ),
    "order_attr": (
        "SELECT o_orderkey AS tid FROM orders",
        _ATTR.format("'st=' || o_orderstatus, 'pr=' || o_orderpriority, 'y=' || year(o_orderdate), 'm=' || month(o_orderdate), 'seg=' || c_mktsegment, 'n=' || n_name", "SELECT o_orderkey AS tid, * FROM orders LEFT JOIN (customer JOIN nation ON c_nationkey = n_nationkey) ON o_custkey = c_custkey"),
    ),
    "part_snation": (
        "SELECT p_partkey AS tid FROM part",
        "SELECT DISTINCT l_partkey AS tid, n_name AS item FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey",
    ),
    "user_key": ("SELECT DISTINCT user_id AS tid FROM events", "SELECT DISTINCT user_id AS tid, json_extract_string(props, '$.k') AS item FROM events"),
    "user_day": (
        "SELECT DISTINCT user_id || '|' || strftime(ts, '%Y-%m-%d') AS tid FROM events",
        "SELECT DISTINCT tid, unnest([event_type, h]) AS item FROM (SELECT user_id || '|' || strftime(ts, '%Y-%m-%d') AS tid, event_type, 'h=' || (hour(ts) // 6) AS h FROM events)",
    ),
    "doc_word": ("SELECT doc_id AS tid FROM documents", "SELECT DISTINCT doc_id AS tid, unnest(regexp_extract_all(lower(text), '\\p{L}{4,}')) AS item FROM documents"),
    "conv_word": (
        "SELECT conv_id || '|' || turn AS tid FROM conversations",
        "SELECT DISTINCT conv_id || '|' || turn AS tid, unnest(list_append(regexp_extract_all(lower(text), '\\p{L}{4,}'), 'role=' || role)) AS item FROM conversations",
    ),
    "page_tag": ("SELECT page_id AS tid FROM pages", "SELECT DISTINCT page_id AS tid, unnest(regexp_extract_all(html, '<([a-z][a-z0-9]*)', 1)) AS item FROM pages"),
    "emb_bin": (
        "SELECT vec_id AS tid FROM embeddings",
        _ATTR.format(", ".join(f"'d{i}=' || ({_BIN.format(i)})" for i in range(1, 13)) + ", 'label=' || label", "SELECT vec_id AS tid, * FROM embeddings"),
    ),
}


def cells(view: str) -> str:
    """CTEs rws(tid), cells(tid, item), nn(n), margin(item, supp)."""
    rows, items = CELLS[view]
    return f"rws AS ({rows}), cells AS MATERIALIZED ({items}), nn AS (SELECT count(*)::DOUBLE AS n FROM rws), margin AS (SELECT item, count(*) AS supp FROM cells GROUP BY item)"


def pairs() -> str:
    """CTE pair(a, b, supp), after cells."""
    return "pair AS (SELECT x.item AS a, y.item AS b, count(*) AS supp FROM cells x JOIN cells y ON x.tid = y.tid AND x.item < y.item GROUP BY ALL)"


def kl(x: str, y: str) -> str:
    part = lambda a, b: f"(CASE WHEN {a} <= 0 THEN 0 WHEN {b} > 0 THEN {a} * log2({a} / {b}) END)"
    return f"({part(x, y)} + {part(f'(1 - {x})', f'(1 - {y})')})"


def masks(view: str, m: int) -> str:
    """CTEs of a view over its m most frequent items: items(item, id, supp), bag(mask, cnt), nn."""
    return (
        f"{cells(view)}, items AS (SELECT item, supp, row_number() OVER (ORDER BY supp DESC, item) - 1 AS id FROM margin QUALIFY id < {m}), "
        "bag AS MATERIALIZED (SELECT mask, count(*)::DOUBLE AS cnt FROM (SELECT rws.tid, coalesce(sum(1 << id), 0)::BIGINT AS mask FROM rws LEFT JOIN (cells JOIN items USING (item)) c ON rws.tid = c.tid GROUP BY rws.tid) GROUP BY mask)"
    )


def name_of(mask: str) -> str:
    return f"(SELECT string_agg(item, '|' ORDER BY item) FROM items WHERE ({mask} >> id) & 1 = 1)"


def support(mask: str) -> str:
    return f"(SELECT coalesce(sum(cnt), 0) FROM bag WHERE bag.mask & ({mask}) = ({mask}))"


#: A constraint holds for the rows with its items or, if it has a size (the least plus 1000 times the most), for those of such sizes.
_INSIDE = "CASE WHEN c.size IS NULL THEN ((i - 1) & c.mask) = c.mask ELSE bit_count((i - 1)::BIGINT) BETWEEN c.size % 1000 AND c.size // 1000 END"


def fit(name: str, m: int, constraints: str, sweeps: int = 60) -> str:
    """CTEs that fit the 2^m row probabilities to constraints(mask, size, fr): {name}(p) has the list.

    One constraint in a step: its rows are scaled to its frequency, the others to the rest.
    """
    return f"""{name}_con AS MATERIALIZED (SELECT mask::BIGINT AS mask, size, fr::DOUBLE AS fr, row_number() OVER (ORDER BY size NULLS FIRST, mask) - 1 AS k, count(*) OVER () AS total FROM ({constraints})),
{name}_steps AS (
  SELECT 0 AS step, list_transform(range(0, {1 << m}), lambda s: 1.0::DOUBLE / {1 << m}) AS p
  UNION ALL
  SELECT step + 1, list_transform(p, lambda x, i: CASE WHEN {_INSIDE} THEN (CASE WHEN mass > 0 THEN x * c.fr / mass ELSE 0 END) ELSE (CASE WHEN mass < 1 THEN x * (1 - c.fr) / (1 - mass) ELSE 0 END) END)
  FROM (SELECT f.step, f.p, c.mask, c.size, c.fr, c.total, list_sum(list_transform(f.p, lambda x, i: CASE WHEN {_INSIDE} THEN x ELSE 0 END)) AS mass FROM {name}_steps f JOIN {name}_con c ON c.k = f.step % c.total) c
  WHERE step < {sweeps} * total
),
{name} AS MATERIALIZED (SELECT arg_max(p, step) AS p FROM {name}_steps)"""


def estimate(p: str, mask: str) -> str:
    """Probability in list `p` of the rows that contain the mask."""
    return f"list_sum(list_transform({p}, lambda x, i: CASE WHEN ((i - 1) & ({mask})) = ({mask}) THEN x ELSE 0 END))"


MARGINS = "SELECT 1 << id AS mask, NULL::INT AS size, supp / n AS fr FROM items, nn"


def row_sizes(m: int, width: int = 1) -> str:
    """Constraints on the number of a row's items, in bins of `width` numbers."""
    return f"SELECT 0 AS mask, (lo + 1000 * least(lo + {width - 1}, {m}))::INT AS size, coalesce((SELECT sum(cnt) FROM bag WHERE bit_count(bag.mask) BETWEEN lo AND lo + {width - 1}), 0) / n AS fr FROM range(0, {m + 1}, {width}) r(lo), nn"
