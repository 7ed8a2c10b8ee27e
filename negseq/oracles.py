"""DuckDB SQL for the queries of the workloads, built from the same few views and shapes."""

from __future__ import annotations

from .operators import generator

_FMT = "CASE WHEN {x} = '' OR regexp_matches({x}, '[\\s()!`]') THEN '`' || replace({x}, '`', '``') || '`' ELSE {x} END"


def fmt(x: str) -> str:
    return _FMT.format(x=x)


_BASKET = """SELECT DISTINCT sid, pos::INTEGER AS pos, item FROM (SELECT o_custkey AS sid, dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderdate) AS pos, {item} AS item
 FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN part ON l_partkey = p_partkey)"""


def _tokens(table: str, sid: str, text: str, pattern: str) -> str:
    return f"SELECT sid, unnest(range(1, len(w) + 1))::INTEGER AS pos, unnest(w) AS item FROM (SELECT {sid} AS sid, regexp_extract_all(lower({text}), '{pattern}', 1) AS w FROM {table}) t"


VIEWS = {
    "clicks": "SELECT user_id AS sid, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id)::INTEGER AS pos, event_type AS item FROM events",
    "kinds": "SELECT user_id AS sid, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id)::INTEGER AS pos, event_type || ':' || least(floor(value / 25)::BIGINT, 3) AS item FROM events",
    "days": "SELECT DISTINCT user_id AS sid, dense_rank() OVER (PARTITION BY user_id ORDER BY ts::DATE)::INTEGER AS pos, event_type AS item FROM events",
    "basket_brand": _BASKET.format(item="p_brand"),
    "basket_type": _BASKET.format(item="p_type"),
    "priority": "SELECT DISTINCT o_custkey AS sid, dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderdate)::INTEGER AS pos, o_orderpriority AS item FROM orders",
    "turns": "SELECT DISTINCT conv_id AS sid, (turn + 1)::INTEGER AS pos, role AS item FROM conversations",
    "words": _tokens("documents", "doc_id", "text", "([a-z]+)"),
    "tags": _tokens("pages", "page_id", "html", "<([a-z][a-z0-9]*)"),
    "nation_flow": """SELECT sid, pos::INTEGER AS pos, item FROM (SELECT l_suppkey AS sid, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_shipdate, l_orderkey, l_linenumber) AS pos, r_name AS item
 FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)""",
    "status_items": """SELECT DISTINCT sid, pos::INTEGER AS pos, item FROM (SELECT o_custkey AS sid, dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderdate) AS pos, l_returnflag || l_linestatus AS item
 FROM orders JOIN lineitem ON o_orderkey = l_orderkey)""",
    "passages": _tokens("benchmark", "item_id", "text", "([a-z]+)"),
    "vec_labels": "SELECT DISTINCT vec_id // 20 AS sid, (vec_id % 20 + 1)::INTEGER AS pos, label::VARCHAR AS item FROM embeddings WHERE label IS NOT NULL",
}

SHAPES = ("x", "(x y)", "x y", "(x y z)", "(x y) z", "x (y z)", "x y z", "x !q y")


def base(view: str, num: int, den: int, where: str = "true") -> str:
    """v, n, t (threshold), f (frequent items), w (view of those)."""
    return f"""v AS MATERIALIZED (SELECT * FROM ({VIEWS[view]}) WHERE {where}), n AS (SELECT count(DISTINCT sid) AS n FROM v), t AS (SELECT (n * {num} + {den - 1}) // {den} AS t FROM n),
f AS (SELECT item, count(DISTINCT sid) AS s FROM v GROUP BY 1 HAVING count(DISTINCT sid) >= (SELECT t FROM t)), w AS MATERIALIZED (SELECT v.* FROM v WHERE item IN (SELECT item FROM f))"""


def reach(a: str, b: str, gap: int | None, span: int | None = None, first: str | None = None) -> str:
    out = f"{b}.sid = {a}.sid AND {b}.pos > {a}.pos"
    if gap is not None:
        out += f" AND {b}.pos <= {a}.pos + {gap}"
    if span is not None:
        out += f" AND {b}.pos - {first or a}.pos <= {span}"
    return out


def shape(kind: str, gap: int | None, span: int | None = None) -> str:
    """pattern, support, n_neg of one shape, over w."""
    x, y, z = fmt("a.item"), fmt("b.item"), fmt("c.item")
    r = lambda p, q, first=None: reach(p, q, gap, span, first)
    of = "count(DISTINCT a.sid) AS support"
    sel = lambda text, tables, keys, neg=0: f"SELECT {text} AS pattern, {of}, {neg} AS n_neg FROM {tables} GROUP BY {keys}"
    same = lambda p, q: f"{q}.sid = {p}.sid AND {q}.pos = {p}.pos AND {q}.item > {p}.item"
    if kind == "x":
        return sel(x, "w a", "a.item")
    if kind == "(x y)":
        return sel(f"'(' || {x} || ' ' || {y} || ')'", f"w a JOIN w b ON {same('a', 'b')}", "a.item, b.item")
    if kind == "x y":
        return sel(f"{x} || ' ' || {y}", f"w a JOIN w b ON {r('a', 'b')}", "a.item, b.item")
    if kind == "(x y z)":
        return sel(f"'(' || {x} || ' ' || {y} || ' ' || {z} || ')'", f"w a JOIN w b ON {same('a', 'b')} JOIN w c ON {same('b', 'c')}", "a.item, b.item, c.item")
    if kind == "(x y) z":
        return sel(f"'(' || {x} || ' ' || {y} || ') ' || {z}", f"w a JOIN w b ON {same('a', 'b')} JOIN w c ON {r('a', 'c')}", "a.item, b.item, c.item")
    if kind == "x (y z)":
        return sel(f"{x} || ' (' || {y} || ' ' || {z} || ')'", f"w a JOIN w b ON {r('a', 'b')} JOIN w c ON {same('b', 'c')}", "a.item, b.item, c.item")
    if kind == "x y z":
        return sel(f"{x} || ' ' || {y} || ' ' || {z}", f"w a JOIN w b ON {r('a', 'b')} JOIN w c ON {r('b', 'c', 'a')}", "a.item, b.item, c.item")
    if kind == "x !q y":
        # of each end, the nearest beginning has the smallest window
        near = f"SELECT a.sid, a.item AS x, b.item AS y, max(a.pos) AS p, b.pos AS e FROM w a JOIN w b ON {r('a', 'b')} GROUP BY a.sid, a.item, b.item, b.pos"
        # a sequence is lost to q if each of its windows holds q
        return f"""WITH near AS MATERIALIZED ({near}), h AS MATERIALIZED (SELECT x, y, count(DISTINCT sid) AS s FROM near GROUP BY 1, 2 HAVING count(DISTINCT sid) >= (SELECT t FROM t)),
 o AS MATERIALIZED (SELECT near.* FROM near JOIN h USING (x, y)), r AS (SELECT sid, x, y, count(*) AS n_rows FROM o GROUP BY 1, 2, 3),
 bad AS (SELECT o.sid, o.x, o.y, m.item AS q, count(DISTINCT o.e) AS n_bad FROM o JOIN w m ON m.sid = o.sid AND m.pos > o.p AND m.pos < o.e GROUP BY 1, 2, 3, 4),
 l AS (SELECT x, y, q, count(*) AS lost FROM bad JOIN r USING (sid, x, y) WHERE n_bad = n_rows GROUP BY 1, 2, 3)
 SELECT {fmt('h.x')} || ' !' || {fmt('i.item')} || ' ' || {fmt('h.y')} AS pattern, h.s - coalesce(l.lost, 0) AS support, 1 AS n_neg FROM h CROSS JOIN f i LEFT JOIN l ON l.x = h.x AND l.y = h.y AND l.q = i.item WHERE h.s - coalesce(l.lost, 0) >= (SELECT t FROM t)"""
    raise ValueError(kind)


def mined(view: str, num: int, den: int, gap: int | None, kinds=SHAPES, span: int | None = None, where: str = "true") -> str:
    """CTEs up to m(pattern, support, n_neg), all frequent patterns of the shapes."""
    parts = " UNION ALL ".join(f"({shape(k, gap, span)}{'' if '!' in k else ' HAVING count(DISTINCT a.sid) >= (SELECT t FROM t)'})" for k in kinds)
    return f"WITH {base(view, num, den, where)}, m AS ({parts})"


def listing(*args, only: str = "true", **kw) -> str:
    return f"{mined(*args, **kw)} SELECT pattern, support::BIGINT AS support FROM m WHERE {only}"


def strict(view: str, num: int, den: int, ratio: tuple[int, int] | None = None, gap: int | None = None) -> str:
    """CTEs up to m: shapes of positives without gaps, and ``x !q y`` by strict occurrence, q strictly between the first x and the last y; ratio: only with a frequent partner."""
    positives = [k for k in SHAPES if "!" not in k]
    text = f"{fmt('h.x')} || ' !' || {fmt('q.item')} || ' ' || {fmt('h.y')}"
    base_ = mined(view, num, den, gap, positives)
    low = "0" if ratio is None else f"((SELECT t FROM t) * {ratio[0]} + {ratio[1] - 1}) // {ratio[1]}"
    # absent items of the partner miner are those of its positive patterns, frequent at the share
    return f"""{base_}, q AS MATERIALIZED ({'SELECT item FROM f' if ratio is None else f'SELECT item FROM v GROUP BY 1 HAVING count(DISTINCT sid) >= {low}'}), qw AS MATERIALIZED (SELECT v.* FROM v WHERE item IN (SELECT item FROM q)), o AS (SELECT a.sid, a.item AS x, b.item AS y, min(a.pos) AS p, max(b.pos) AS e FROM w a JOIN w b ON b.sid = a.sid AND b.pos > a.pos GROUP BY 1, 2, 3),
 h AS (SELECT x, y, count(*) AS s FROM o GROUP BY 1, 2 HAVING count(*) >= (SELECT t FROM t)),
 lost AS (SELECT x, y, m.item AS q, count(DISTINCT o.sid) AS lost FROM o JOIN qw m ON m.sid = o.sid AND m.pos > o.p AND m.pos < o.e GROUP BY 1, 2, 3),
 g AS (SELECT {text} AS pattern, h.s - coalesce(lost, 0) AS support, 1 AS n_neg, coalesce(lost, 0) AS partner FROM h CROSS JOIN q LEFT JOIN lost ON lost.x = h.x AND lost.y = h.y AND lost.q = q.item WHERE h.s - coalesce(lost, 0) >= (SELECT t FROM t) AND coalesce(lost, 0) >= {low})"""


def holders(p, gap: int | None = None, span: int | None = None, view: str = "v") -> str:
    """The distinct sequences of a view that hold a pattern, under total absence and soft occurrence."""
    tables, where = [], []
    for k, items in enumerate(p.positives):
        for j, x in enumerate(items):
            tables.append(f"{view} e{k}_{j}")
            where.append(f"e{k}_{j}.item = '{x}'")
            if j:
                where.append(f"e{k}_{j}.sid = e{k}_0.sid AND e{k}_{j}.pos = e{k}_0.pos")
        if k:
            where.append(reach(f"e{k - 1}_0", f"e{k}_0", gap, span, "e0_0"))
    for k, q in enumerate(p.absences):
        if q:
            where.append(f"NOT EXISTS (SELECT 1 FROM {view} m WHERE m.sid = e0_0.sid AND m.pos > e{k}_0.pos AND m.pos < e{k + 1}_0.pos AND m.item IN ({', '.join(map(repr, q))}))")
    return f"SELECT DISTINCT e0_0.sid FROM {', '.join(tables)} WHERE {' AND '.join(where)}"


def uniform(seed: int, *parts: str) -> str:
    return f"(('0x' || substr(md5(concat_ws(':', '{seed}', {', '.join(parts)})), 1, 8))::BIGINT / {float(2**32)!r}::DOUBLE)"


def synthetic(seed: int, n: int = 500, mean_len: int = 20, n_items: int = 20, n_patterns: int = 3, pattern_len: int = 4, min_freq: float = 0.10) -> str:
    """The generator's rows (sid, pos, item)."""
    patterns, names = generator.plan(n_items, n_patterns, pattern_len, seed), generator.names(n_items)
    longest = max(len(p.elements) for p in patterns) + 1
    steps = ", ".join(map(repr, generator.poisson_steps(mean_len)))
    out = f"SELECT sid, greatest({longest}, len(list_filter([{steps}]::DOUBLE[], lambda s: s <= l)))::INTEGER AS len FROM (SELECT sid, {uniform(seed, 'sid', '0')} AS l FROM range({n}) r(sid))"
    out = f"SELECT sid, len, unnest(range(1, len + 1)) AS i FROM ({out})"
    out = f"SELECT sid, len, i, [{', '.join(map(repr, names))}][floor({uniform(seed, 'sid', 'i')} * {n_items})::INTEGER + 1] AS item FROM ({out})"
    for k, p in enumerate(patterns):
        m = len(p.positives)
        at = ", ".join(f"(floor(({j} + {uniform(seed + k, 'sid', str(1000 + j))} * 0.999::DOUBLE) * len / {m}) + 1)::INTEGER AS p{j}" for j in range(m))
        put = " ".join([f"WHEN i = p{j} THEN '{x}'" for j, (x,) in reversed(list(enumerate(p.positives)))] + [f"WHEN i > p{j} AND i < p{j + 1} AND item = '{q[0]}' THEN '{names[(names.index(q[0]) + 1) % n_items]}'" for j, q in reversed(list(enumerate(p.absences))) if q])
        out = f"SELECT sid, len, i, CASE WHEN NOT planted THEN item {put} ELSE item END AS item FROM (SELECT *, {uniform(seed + 7919 * (k + 1), 'sid')} < {min(1.0, 1.2 * min_freq)!r}::DOUBLE AS planted, {at} FROM ({out}))"
    return f"SELECT sid, i::INTEGER AS pos, item FROM ({out})"


def sql() -> dict[str, str]:
    from . import workloads

    return workloads.SQL
