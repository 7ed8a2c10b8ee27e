"""Queries by name: each method, variant, baseline, measure and experiment on the given tables, and SQL for what SQL can say.

``QUERIES[name](spark, sf_dir)`` returns plain columns; ``SQL[name]`` is the same for DuckDB.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import oracles as O
from .functions.pattern import parse
from .functions.semantics import ALL, FREE, GROWTH, Constraints, Semantics
from .operators import baselines, bit_engine, generator, growth, local_engine, matching, measures, postprocess
from .operators import sequences as S
from .operators.growth import Options
from .plans.planner import small
from .plans.stage import written

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return add


def mined(spark: SparkSession, d: str, view: str, sigma, options: Options, **kw) -> DataFrame:
    return growth.mine(S.VIEWS[view](spark, d), sigma, options, **kw)


def plain(df: DataFrame, where: str = "true") -> DataFrame:
    return df.where(where).select("pattern", F.col("support").cast("long").alias("support"))


def nested(spark: SparkSession, d: str, view: str) -> DataFrame:
    return S.nested(S.VIEWS[view](spark, d))


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Brand baskets, half of the customers, gaps up to 3, three items."""
    return plain(mined(spark, d, "basket_brand", "0.5", Options(maxgap=3)))


# ---- worked examples, on the given tables


def _held(view: str, pattern: str, semantics: tuple[Semantics, ...]) -> str:
    """SQL for rows (sid, pattern, semantics) of ``x !q y`` with any set q: for each pair of places, which items of q are in one itemset or in the window."""
    p = parse(pattern)
    x, y, q = p.positives[0][0], p.positives[1][0], p.absences[0]
    items = ", ".join(map(repr, q))
    out = []
    for s in semantics:
        inside = "m.sid = o.sid AND m.pos > o.p AND m.pos < o.e"
        if s.non_inclusion == "total":
            bad = f"EXISTS (SELECT 1 FROM v m WHERE {inside} AND m.item IN ({items}))"
        elif s.embedding == "strict":
            bad = f"(SELECT count(DISTINCT m.item) FROM v m WHERE {inside} AND m.item IN ({items})) = {len(q)}"
        else:
            bad = f"EXISTS (SELECT 1 FROM v m WHERE {inside} AND m.item IN ({items}) GROUP BY m.pos HAVING count(DISTINCT m.item) = {len(q)})"
        label = f"{s.non_inclusion} {s.embedding} {s.occurrence}"
        keep = f"bool_or(NOT {bad})" if s.occurrence == "soft" else f"bool_and(NOT {bad})"
        out.append(f"SELECT sid, '{pattern}' AS pattern, '{label}' AS semantics FROM (SELECT a.sid, a.pos AS p, b.pos AS e FROM v a JOIN v b ON a.sid = b.sid AND a.pos < b.pos WHERE a.item = '{x}' AND b.item = '{y}') o GROUP BY sid HAVING {keep}")
    return f"WITH v AS MATERIALIZED ({O.VIEWS[view]}) " + " UNION ALL ".join(out)


def _holders(spark: SparkSession, d: str, view: str, patterns: list[str], semantics: tuple[Semantics, ...]) -> DataFrame:
    flags = F.array(*(F.when(matching.occurs("itemsets", p, s), F.struct(F.lit(p).alias("pattern"), F.lit(f"{s.non_inclusion} {s.embedding} {s.occurrence}").alias("semantics"))) for p in patterns for s in semantics))
    return nested(spark, d, view).select("sid", F.explode(F.filter(flags, lambda x: x.isNotNull())).alias("x")).select("sid", "x.pattern", "x.semantics")


INCLUSION = ["click !error signup", "click !(error purchase) signup", "click !(error purchase view) signup", "click !(error nothing purchase view) signup"]
SOFT = tuple(s for s in ALL if s.occurrence == "soft")
query("inclusion_table", " UNION ALL ".join(f"SELECT * FROM ({_held('days', p, SOFT)})" for p in INCLUSION))(lambda spark, d: _holders(spark, d, "days", INCLUSION, SOFT))
query("absence_table", _held("days", "error !(click view) purchase", ALL))(lambda spark, d: _holders(spark, d, "days", ["error !(click view) purchase"], ALL))


@query("occurrence_table", f"""WITH v AS ({O.VIEWS['priority']}) SELECT a.sid, concat_ws(',', a.pos, b.pos, c.pos) AS positions, NOT EXISTS (SELECT 1 FROM v m WHERE m.sid = a.sid AND m.pos > b.pos AND m.pos < c.pos AND m.item = '3-MEDIUM') AS ok
FROM v a JOIN v b ON a.sid = b.sid AND a.pos < b.pos JOIN v c ON a.sid = c.sid AND b.pos < c.pos WHERE a.item = '1-URGENT' AND b.item = '2-HIGH' AND c.item = '5-LOW'""")  # fmt: skip
def occurrence_table(spark: SparkSession, d: str) -> DataFrame:
    return matching.negative_embeddings(nested(spark, d, "priority"), "1-URGENT 2-HIGH !3-MEDIUM 5-LOW").select("sid", F.concat_ws(",", F.col("e").cast("array<string>")).alias("positions"), "ok")


def _strict_one(pattern: str) -> str:
    """Support of a pattern with one absence under strict occurrence: no embedding of its positive part has the absent item in the gap."""
    p = parse(pattern)
    gap = next(k for k, q in enumerate(p.absences) if q)
    at = f"v m WHERE m.sid = e0_0.sid AND m.pos > e{gap}_0.pos AND m.pos < e{gap + 1}_0.pos AND m.item IN ({', '.join(map(repr, p.absences[gap]))})"
    whole = O.holders(p.positive_part())
    bad = whole.replace("SELECT DISTINCT e0_0.sid", "SELECT e0_0.sid") + f" AND EXISTS (SELECT 1 FROM {at})"
    return f"SELECT 'strict' AS occurrence, '{pattern}' AS pattern, (SELECT count(*) FROM ({whole}) WHERE sid NOT IN ({bad}))::BIGINT AS support"


#: Under soft and strict occurrence: a larger pattern and a smaller one, where the larger may hold without the smaller.
SOFT_ORDER, STRICT_ORDER = ("2-HIGH !3-MEDIUM 5-LOW 1-URGENT", "2-HIGH !3-MEDIUM 1-URGENT"), ("1-URGENT (2-HIGH 3-MEDIUM) !3-MEDIUM 5-LOW", "1-URGENT 2-HIGH !3-MEDIUM 5-LOW", "1-URGENT !2-HIGH 5-LOW 3-MEDIUM", "1-URGENT !2-HIGH 5-LOW")
_SOFT_ORDER = " UNION ALL ".join(f"SELECT 'soft' AS occurrence, '{parse(p).text}' AS pattern, (SELECT count(*) FROM ({O.holders(parse(p))}))::BIGINT AS support" for p in SOFT_ORDER)
_STRICT_ORDER = " UNION ALL ".join(_strict_one(p) for p in STRICT_ORDER)


@query("monotonicity_cases", f"WITH v AS MATERIALIZED ({O.VIEWS['priority']}) {_SOFT_ORDER} UNION ALL {_STRICT_ORDER}")
def monotonicity_cases(spark: SparkSession, d: str) -> DataFrame:
    """Supports of a larger pattern and of a smaller one; either may be greater."""
    sequences = nested(spark, d, "priority")
    soft = matching.support(sequences, list(SOFT_ORDER)).select(F.lit("soft").alias("occurrence"), "pattern", "support")
    strict = matching.support(sequences, list(STRICT_ORDER), Semantics("total", "soft", "strict")).select(F.lit("strict").alias("occurrence"), "pattern", "support")
    return soft.unionAll(strict)


query("exec_example", O.listing("priority", 1, 2, None))(lambda spark, d: plain(mined(spark, d, "priority", "0.5", Options())))


@query("rematch_case", f"""WITH v AS ({O.VIEWS['priority']}) SELECT sid, positions FROM (SELECT a.sid, concat_ws(',', a.pos, b.pos, c.pos) AS positions, row_number() OVER (PARTITION BY a.sid ORDER BY a.pos, b.pos, c.pos) AS k FROM v a JOIN v b ON a.sid = b.sid AND a.pos < b.pos JOIN v c ON a.sid = c.sid AND b.pos < c.pos
WHERE a.item = '1-URGENT' AND b.item = '2-HIGH' AND c.item = '3-MEDIUM' AND NOT EXISTS (SELECT 1 FROM v m WHERE m.sid = a.sid AND m.pos > b.pos AND m.pos < c.pos AND m.item = '5-LOW')) WHERE k = 1""")
def rematch_case(spark: SparkSession, d: str) -> DataFrame:
    return matching.next_match(nested(spark, d, "priority"), "1-URGENT 2-HIGH !5-LOW 3-MEDIUM").select("sid", F.concat_ws(",", F.col("e").cast("array<string>")).alias("positions"))


#: The steps that lead to one pattern: pattern, parent, step.
PATH = (("click", "", "root"), ("click error", "click", "s"), ("click !signup error", "click error", "n"), ("click !signup error purchase", "click !signup error", "s"), ("click !signup error (purchase view)", "click !signup error purchase", "c"))
_PATH = " UNION ALL ".join(f"SELECT '{p}' AS pattern, '{up}' AS parent_pattern, '{op}' AS op, (SELECT count(*) FROM ({O.holders(parse(p))}))::BIGINT AS support" for p, up, op in PATH)


@query("derivation_path", f"WITH {O.base('days', 1, 2)} SELECT * FROM ({_PATH}) WHERE support >= (SELECT t FROM t)")
def derivation_path(spark: SparkSession, d: str) -> DataFrame:
    """Of the tree below click."""
    tree = growth.trace(S.days(spark, d), "0.5", Options(max_items=5, max_pos_items=4, max_itemsets=3, prefix="click", surround="checked"))
    return tree.where(F.col("pattern").isin([p for p, *_ in PATH])).select("pattern", F.coalesce("parent_pattern", F.lit("")).alias("parent_pattern"), "op", "support")


#: What each shape grew from, and by which step.
_I = "(`[^`]*`|[^\\s()!`]+)"
_GREW = {k.replace('(w)', _I): x for k, x in {"^(w)$": ("", "root"), "^\\((w) (w)\\)$": ("\\1", "c"), "^(w) (w)$": ("\\1", "s"), "^\\((w) (w) (w)\\)$": ("(\\1 \\2)", "c"), "^\\((w) (w)\\) (w)$": ("(\\1 \\2)", "s"), "^(w) \\((w) (w)\\)$": ("\\1 \\2", "c"), "^(w) (w) (w)$": ("\\1 \\2", "s"), "^(w) !(w) (w)$": ("\\1 \\3", "n")}.items()}


def _grew(what: int) -> str:
    return "CASE " + " ".join(f"WHEN regexp_matches(pattern, '{r}') THEN " + (f"regexp_replace(pattern, '{r}', '{to[0]}')" if what == 0 else f"'{to[1]}'") for r, to in _GREW.items()) + " END"


@query("search_tree", f"SELECT pattern, {_grew(0)} AS parent_pattern, {_grew(1)} AS op, support FROM ({O.listing('priority', 1, 2, None)})")
def search_tree(spark: SparkSession, d: str) -> DataFrame:
    return growth.trace(S.priority(spark, d), "0.5", Options()).select("pattern", F.coalesce("parent_pattern", F.lit("")).alias("parent_pattern"), "op", "support")


# ---- views

for _name, _view in S.VIEWS.items():
    query(f"build_{_name}", O.VIEWS[_name])(lambda spark, d, v=_view: v(spark, d))
    query(f"frequent_items_{_name}", f"WITH {O.base(_name, 1, 10)} SELECT item, s::BIGINT AS support FROM f")(lambda spark, d, v=_view: growth.frequent_items(items := v(spark, d), growth.threshold(growth.n_sequences(items), "0.1")))

PROFILED = ("clicks", "kinds", "days", "basket_brand", "basket_type", "priority", "turns", "words", "tags")
_PROFILE = """SELECT '{name}' AS name, count(*)::BIGINT AS sequences, round(avg(len), 6) AS mean_len, round(coalesce(stddev(len), 0), 6) AS sd_len, max(len)::BIGINT AS max_len, round(sum(wide) / sum(sets), 6) AS mean_width, any_value(alphabet)::BIGINT AS alphabet
FROM (SELECT sid, max(pos) AS len, count(*) AS wide, count(DISTINCT pos) AS sets FROM ({view}) GROUP BY sid), (SELECT count(DISTINCT item) AS alphabet FROM ({view}))"""


@query("profile_views", " UNION ALL ".join(_PROFILE.format(name=n, view=O.VIEWS[n]) for n in PROFILED))
def profile_views(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for n in PROFILED:
        one = measures.profile(S.VIEWS[n](spark, d)).select(F.lit(n).alias("name"), "sequences", "mean_len", "sd_len", "max_len", "mean_width", "alphabet")
        out = one if out is None else out.unionAll(one)
    return out


# ---- growth miner and its variants

POSITIVE = tuple(k for k in O.SHAPES if "!" not in k)
query("mine_pairs", O.listing("priority", 1, 2, 3, ("x", "(x y)", "x y")))(lambda spark, d: plain(mined(spark, d, "priority", "0.5", Options(maxgap=3, max_items=2))))
query("mine_itemset_pairs", O.listing("days", 1, 2, 3, ("(x y) z",)))(lambda spark, d: plain(mined(spark, d, "days", "0.5", Options(maxgap=3, negatives=False)), "n_pos = 2 and n_items = 3 and pattern like '(%) %'").where("pattern rlike '^\\\\(\\\\S+ \\\\S+\\\\) \\\\S+$'"))
query("mine_triples", O.listing("priority", 3, 10, 3, POSITIVE))(lambda spark, d: plain(mined(spark, d, "priority", "0.3", Options(maxgap=3, negatives=False))))
query("mine_one_negative", O.listing("priority", 1, 2, None, only="n_neg = 1"))(lambda spark, d: plain(mined(spark, d, "priority", "0.5", Options()), "n_neg = 1"))
query("mine_one_negative_maxgap", O.listing("words", 1, 5, 3, only="n_neg = 1"))(lambda spark, d: plain(mined(spark, d, "words", "0.2", Options(maxgap=3)), "n_neg = 1"))
query("mine_one_negative_maxspan", O.listing("basket_brand", 2, 5, None, span=3, only="n_neg = 1"))(lambda spark, d: plain(mined(spark, d, "basket_brand", "0.4", Options(maxspan=3)), "n_neg = 1"))

_TWO_Q = f"""WITH {O.base('basket_type', 1, 2)}, o AS (SELECT a.sid, a.item AS x, b.item AS y, max(a.pos) AS p, b.pos AS e FROM w a JOIN w b ON {O.reach('a', 'b', 3)} GROUP BY a.sid, a.item, b.item, b.pos)
SELECT {O.fmt('x')} || ' !(' || {O.fmt('q.item')} || ' ' || {O.fmt('r.item')} || ') ' || {O.fmt('y')} AS pattern, count(DISTINCT sid)::BIGINT AS support FROM o, f q JOIN f r ON q.item < r.item
WHERE NOT EXISTS (SELECT 1 FROM w m WHERE m.sid = o.sid AND m.pos > p AND m.pos < e AND m.item IN (q.item, r.item)) GROUP BY x, y, q.item, r.item HAVING count(DISTINCT sid) >= (SELECT t FROM t)"""
query("mine_two_item_negative", _TWO_Q)(lambda spark, d: plain(mined(spark, d, "basket_type", "0.5", Options(maxgap=3, max_items=4, max_neg_size=2, max_pos_items=2, max_itemsets=2)), "n_neg = 1 and n_items = 4 and n_pos = 2"))

_TWO_NEG = f"""WITH {O.base('turns', 1, 5)}, o AS (SELECT a.sid, a.pos AS p1, b.pos AS p2, c.pos AS p3, a.item AS x, b.item AS y, c.item AS z FROM w a JOIN w b ON {O.reach('a', 'b', None)} JOIN w c ON {O.reach('b', 'c', None)})
SELECT {O.fmt('x')} || ' !' || {O.fmt('q.item')} || ' ' || {O.fmt('y')} || ' !' || {O.fmt('r.item')} || ' ' || {O.fmt('z')} AS pattern, count(DISTINCT sid)::BIGINT AS support FROM o, f q, f r
WHERE NOT EXISTS (SELECT 1 FROM w m WHERE m.sid = o.sid AND ((m.pos > p1 AND m.pos < p2 AND m.item = q.item) OR (m.pos > p2 AND m.pos < p3 AND m.item = r.item))) GROUP BY x, y, z, q.item, r.item HAVING count(DISTINCT sid) >= (SELECT t FROM t)"""
query("mine_two_negatives", _TWO_NEG)(lambda spark, d: plain(mined(spark, d, "turns", "0.2", Options(max_items=5)), "n_neg = 2 and n_pos = 3 and n_items = 5"))


def _partial(strict: bool, lset: str) -> str:
    """x !(q r) y with the pairs of lset absent in part, on basket_type."""
    bad = "SELECT count(DISTINCT m.item) FROM w m WHERE m.sid = o.sid AND m.pos > p AND m.pos < e AND m.item IN (l.q, l.r)"
    clean = f"({bad}) < 2" if strict else f"NOT EXISTS ({bad} GROUP BY m.pos HAVING count(DISTINCT m.item) = 2)"
    return f"""WITH {O.base('basket_type', 1, 2)}, o AS (SELECT a.sid, a.item AS x, b.item AS y, max(a.pos) AS p, b.pos AS e FROM w a JOIN w b ON {O.reach('a', 'b', 3)} GROUP BY a.sid, a.item, b.item, b.pos), l AS ({lset})
SELECT {O.fmt('x')} || ' !(' || {O.fmt('l.q')} || ' ' || {O.fmt('l.r')} || ') ' || {O.fmt('y')} AS pattern, count(DISTINCT sid)::BIGINT AS support FROM o, l WHERE {clean} GROUP BY x, y, l.q, l.r HAVING count(DISTINCT sid) >= (SELECT t FROM t)"""


_PAIRS = "SELECT a.item AS q, b.item AS r FROM f a JOIN f b ON a.item < b.item"
_SETS = "SELECT a.item AS q, b.item AS r FROM w a JOIN w b ON a.sid = b.sid AND a.pos = b.pos AND a.item < b.item GROUP BY 1, 2 HAVING count(DISTINCT a.sid) >= (SELECT t FROM t)"
PARTIAL = Options(maxgap=3, max_items=4, max_neg_size=2, max_pos_items=2, max_itemsets=2, non_inclusion="partial")


def _pairs_of_items(spark: SparkSession, packed: bit_engine.Packed, minsup: int) -> DataFrame:
    f = spark.createDataFrame([(x,) for x in packed.supports(minsup)], "item string")
    return f.join(f.select(F.col("item").alias("other")), F.col("item") < F.col("other")).select(F.array("item", "other").alias("items"))


def _mine_partial(spark: SparkSession, d: str, embedding: str, itemsets: bool = False) -> DataFrame:
    """On sequences that are packed once, for the sets to be absent too."""
    from dataclasses import replace

    items = S.basket_type(spark, d)
    packed = bit_engine.pack(items)
    minsup = max(1, growth.threshold(packed.n, "0.5"))
    if itemsets:
        lminus = growth.frequent_itemsets(items, minsup, 2, packed).where(F.size("items") == 2).select("items")
    else:
        lminus = _pairs_of_items(spark, packed, minsup)
    return plain(growth.mine(items, minsup, replace(PARTIAL, embedding=embedding), lminus, packed=packed), "n_neg = 1")


query("mine_partial_soft", _partial(False, _PAIRS))(lambda spark, d: _mine_partial(spark, d, "soft"))
query("mine_partial_strict", _partial(True, _PAIRS))(lambda spark, d: _mine_partial(spark, d, "strict"))
query("mine_lminus_itemsets", _partial(False, _SETS))(lambda spark, d: _mine_partial(spark, d, "soft", True))
query("mine_lminus_user", O.listing("priority", 1, 2, 3, only="n_neg = 1 AND (pattern LIKE '%!1-URGENT %' OR pattern LIKE '%!2-HIGH %')"))(
    lambda spark, d: plain(mined(spark, d, "priority", "0.5", Options(maxgap=3), lminus=spark.createDataFrame([(["1-URGENT"],), (["2-HIGH"],), (["unknown"],)], "items array<string>")), "n_neg = 1")
)
_AROUND = "regexp_matches(pattern, '^(`[^`]*`|\\S+) !(`[^`]*`|\\S+) (`[^`]*`|\\S+)$')"
_PART = "regexp_extract(pattern, '^(`[^`]*`|\\S+) !(`[^`]*`|\\S+) (`[^`]*`|\\S+)$', {})"
query("mine_no_surround", O.listing("priority", 1, 2, 3, only=f"n_neg = 0 OR ({_PART.format(2)} <> {_PART.format(1)} AND {_PART.format(2)} <> {_PART.format(3)})"))(lambda spark, d: plain(mined(spark, d, "priority", "0.5", Options(maxgap=3, surround="checked"))))
query("mine_drop_last", O.listing("priority", 1, 2, 3, only=f"n_neg = 0 OR {_PART.format(2)} <> {_PART.format(3)}"))(lambda spark, d: plain(mined(spark, d, "priority", "0.5", Options(maxgap=3, redundancy="drop_last"))))
query("mine_seeded", O.listing("basket_brand", 2, 5, 3, only="pattern = 'Brand#13' OR pattern LIKE 'Brand#13 %' OR pattern LIKE '(Brand#13 %'"))(lambda spark, d: plain(mined(spark, d, "basket_brand", "0.4", Options(maxgap=3, prefix="Brand#13"))))
query("mine_strict_occurrence", f"{O.strict('priority', 1, 5)} SELECT pattern, support::BIGINT AS support FROM (SELECT pattern, support FROM m UNION ALL SELECT pattern, support FROM g)")(lambda spark, d: plain(baselines.mine_strict(S.priority(spark, d), "0.2", Options())))
_STRICT_TWO = f"""WITH {O.base('turns', 1, 5)}, o AS (SELECT a.sid, a.pos AS p1, b.pos AS p2, c.pos AS p3, a.item AS x, b.item AS y, c.item AS z FROM w a JOIN w b ON {O.reach('a', 'b', 3)} JOIN w c ON {O.reach('b', 'c', 3)}),
h AS (SELECT DISTINCT sid, x, y, z FROM o), v1 AS (SELECT DISTINCT o.sid, x, y, z, m.item AS q FROM o JOIN w m ON m.sid = o.sid AND m.pos > p1 AND m.pos < p2), v2 AS (SELECT DISTINCT o.sid, x, y, z, m.item AS q FROM o JOIN w m ON m.sid = o.sid AND m.pos > p2 AND m.pos < p3)
SELECT {O.fmt('x')} || ' !' || {O.fmt('q.item')} || ' ' || {O.fmt('y')} || ' !' || {O.fmt('r.item')} || ' ' || {O.fmt('z')} AS pattern, count(*)::BIGINT AS support FROM h, f q, f r WHERE (sid, x, y, z, q.item) NOT IN (SELECT (sid, x, y, z, q) FROM v1) AND (sid, x, y, z, r.item) NOT IN (SELECT (sid, x, y, z, q) FROM v2) GROUP BY x, y, z, q.item, r.item HAVING count(*) >= (SELECT t FROM t)"""
query("mine_strict_two_absences", _STRICT_TWO)(lambda spark, d: plain(baselines.mine_strict(S.turns(spark, d), "0.2", Options(maxgap=3, max_items=5)), "n_neg = 2 and n_pos = 3 and n_items = 5"))
FULL = O.listing("basket_brand", 2, 5, 3)
query("mine_frontier", FULL)(lambda spark, d: plain(mined(spark, d, "basket_brand", "0.4", Options(maxgap=3), engine="frontier")))
query("mine_growth_full", FULL)(lambda spark, d: plain(mined(spark, d, "basket_brand", "0.4", Options(maxgap=3))))
query("mine_growth_local", FULL)(lambda spark, d: plain(local_engine.mine_by_root(S.basket_brand(spark, d), "0.4", Options(maxgap=3))))
query("mine_growth_hybrid", O.listing("priority", 1, 2, 3))(lambda spark, d: _hybrid(S.priority(spark, d)))


def _hybrid(items: DataFrame) -> DataFrame:
    """The largest root does not fit a task."""
    most = local_engine.root_sizes(items, 1).agg(F.max("rows")).first()[0]
    return plain(local_engine.mine_hybrid(items, "0.5", Options(maxgap=3), local_rows=(most or 1) - 1))



# ---- baselines

_ALL = "SELECT pattern, support::BIGINT AS support FROM (SELECT pattern, support FROM m UNION ALL SELECT pattern, support FROM g)"
for _ratio, _tag in ((0.7, "070"), (1.0, "100"), (0.2, "020")):
    query(f"partner_mine_{_tag}", f"{O.strict('tags', 1, 2, (int(_ratio * 10), 10))} {_ALL}")(lambda spark, d, r=_ratio: plain(baselines.mine_partner(S.tags(spark, d), "0.5", r)))
query("partner_item_unit", f"{O.strict('priority', 1, 5, (7, 10))} {_ALL}")(lambda spark, d: plain(baselines.mine_partner(S.priority(spark, d), "0.2", 0.7, unit="item")))
_LONE = "SELECT '!' || {0} AS pattern, (n - s)::BIGINT AS support FROM (SELECT item, count(DISTINCT sid) AS s FROM v GROUP BY 1), n, t WHERE 10 * s >= 7 * t AND n - s >= t"
query("partner_boundary", f"{O.strict('turns', 1, 5, (7, 10))} {_ALL} UNION ALL {_LONE.format(O.fmt('item'))}")(lambda spark, d: plain(baselines.mine_partner(S.turns(spark, d), "0.2", 0.7, boundary=True)))
query("partner_frontier", f"{O.strict('priority', 1, 5, (7, 10))} {_ALL}")(lambda spark, d: plain(baselines.mine_partner(S.priority(spark, d), "0.2", 0.7, engine="frontier")))
LEVELS = O.listing("priority", 1, 2, 3)
query("levelwise_total", LEVELS)(lambda spark, d: plain(baselines.mine_levelwise(nested(spark, d, "priority"), "0.5", c=Constraints(3))))
query("levelwise_items", O.listing("turns", 1, 20, None))(lambda spark, d: plain(baselines.mine_levelwise(nested(spark, d, "turns"), "0.05", max_neg_size=1)))
query("mllib_positive", O.listing("priority", 3, 10, None, POSITIVE))(lambda spark, d: plain(baselines.mine_positive_library(nested(spark, d, "priority"), "0.3")))

# ---- supports of given patterns


def _support(view: str, pattern: str, sem: Semantics, c: Constraints = FREE) -> tuple[str, Callable]:
    """One pattern of two or three positive single items with absences between the first two."""
    p = parse(pattern)
    (x,), (y,) = p.positives
    q = p.absences[0]
    items = ", ".join(map(repr, q))
    inside = "m.sid = o.sid AND m.pos > o.p AND m.pos < o.e"
    if sem.non_inclusion == "total":
        bad = f"EXISTS (SELECT 1 FROM v m WHERE {inside} AND m.item IN ({items}))"
    elif sem.embedding == "strict":
        bad = f"(SELECT count(DISTINCT m.item) FROM v m WHERE {inside} AND m.item IN ({items})) = {len(q)}"
    else:
        bad = f"EXISTS (SELECT 1 FROM v m WHERE {inside} AND m.item IN ({items}) GROUP BY m.pos HAVING count(DISTINCT m.item) = {len(q)})"
    keep = "bool_or(NOT b)" if sem.occurrence == "soft" else "bool_and(NOT b)"
    text = p.text.replace("'", "''")
    return f"""WITH v AS ({O.VIEWS[view]}), o AS (SELECT a.sid, a.pos AS p, b.pos AS e FROM v a JOIN v b ON {O.reach('a', 'b', c.maxgap, c.maxspan)} WHERE a.item = '{x}' AND b.item = '{y}'), r AS (SELECT sid, {bad} AS b FROM o)
SELECT '{text}' AS pattern, (SELECT count(*) FROM (SELECT sid FROM r GROUP BY sid HAVING {keep}))::BIGINT AS support""", lambda spark, d: plain(matching.support(nested(spark, d, view), [p], sem, c))


for _name, _args in {
    "support_one_negative": ("basket_brand", "Brand#13 !Brand#11 Brand#13", GROWTH),
    "support_maxgap": ("basket_brand", "Brand#13 !Brand#11 Brand#13", GROWTH, Constraints(3)),
    "support_itemset_negative": ("days", "click !(error view) click", GROWTH),
    "support_strict_occ": ("days", "click !error click", Semantics("total", "soft", "strict"), Constraints(2)),
    "support_partial_soft": ("days", "click !(error view) click", Semantics("partial", "soft", "strict")),
    "support_partial_strict": ("days", "click !(error view) click", Semantics("partial", "strict", "strict")),
    "support_maxspan": ("basket_brand", "Brand#13 !Brand#11 Brand#12", GROWTH, Constraints(None, 2)),
}.items():
    _sql, _run = _support(*_args)
    query(_name, _sql)(_run)

query("support_two_negatives", f"""WITH v AS ({O.VIEWS['basket_type']}), p AS (SELECT any_value(i1) AS a, any_value(i2) AS b FROM (SELECT min(item) AS i1, max(item) AS i2 FROM v)),
o AS (SELECT x.sid, x.pos AS p1, y.pos AS p2, z.pos AS p3 FROM v x JOIN v y ON {O.reach('x', 'y', 3)} JOIN v z ON {O.reach('y', 'z', 3)}, p WHERE x.item = p.a AND y.item = p.b AND z.item = p.a)
SELECT 'least !greatest greatest !least least' AS pattern, count(DISTINCT sid)::BIGINT AS support FROM o, p WHERE NOT EXISTS (SELECT 1 FROM v m WHERE m.sid = o.sid AND ((m.pos > p1 AND m.pos < p2 AND m.item = p.b) OR (m.pos > p2 AND m.pos < p3 AND m.item = p.a)))""")(  # fmt: skip
    lambda spark, d: _two_negatives(spark, d)
)


def _two_negatives(spark: SparkSession, d: str) -> DataFrame:
    from .functions.pattern import build

    a, b = S.basket_type(spark, d).agg(F.min("item"), F.max("item")).first()
    p = build([(False, [a]), (True, [b]), (False, [b]), (True, [a]), (False, [a])])
    return matching.support(nested(spark, d, "basket_type"), [p], GROWTH, Constraints(3)).select(F.lit("least !greatest greatest !least least").alias("pattern"), "support")


COMPARED = "click !(error view) signup"
_COMPARE = []
for _s in ALL:
    _q = _support("days", COMPARED, _s, Constraints(4))[0]
    _COMPARE.append(f"SELECT pattern, '{_s.non_inclusion}' AS non_inclusion, '{_s.embedding}' AS embedding, '{_s.occurrence}' AS occurrence, support FROM ({_q})")
query("compare_semantics", " UNION ALL ".join(_COMPARE))(lambda spark, d: matching.compare_semantics(nested(spark, d, "days"), [COMPARED], ALL, Constraints(4)))
query("semantics_counts", f"SELECT non_inclusion, embedding, occurrence, sum(CASE WHEN support >= 75 THEN 1 ELSE 0 END)::BIGINT AS frequent, sum(support)::BIGINT AS total FROM ({' UNION ALL '.join(_COMPARE)}) GROUP BY 1, 2, 3")(
    lambda spark, d: _semantics_counts(nested(spark, d, "days"))
)


def _semantics_counts(days: DataFrame) -> DataFrame:
    """Frequent: held by half of the sequences."""
    half = F.when(F.col("support") >= growth.threshold(days.count(), "0.5"), 1).otherwise(0)
    return matching.compare_semantics(days, [COMPARED], ALL, Constraints(4)).groupBy("non_inclusion", "embedding", "occurrence").agg(F.sum(half).cast("long").alias("frequent"), F.sum("support").alias("total"))

# ---- comparison of mined sets

_GAP = O.mined("priority", 1, 5, 3)[len("WITH ") :].replace("v AS", "v AS", 1)
_FREE_STRICT = O.strict("priority", 1, 5, (7, 10))


def _both(select: str) -> str:
    """gm: growth with maxgap 3; pm: partner, on priority at 20 %."""
    return f"WITH gm AS (SELECT * FROM ({O.listing('priority', 1, 5, 3)})), pm AS (SELECT * FROM ({_FREE_STRICT} {_ALL})) {select}"


def _pair(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    items = S.priority(spark, d)
    return growth.mine(items, "0.2", Options(maxgap=3)), baselines.mine_partner(items, "0.2", 0.7)


query("overlap", _both("SELECT pattern, coalesce(gm.support, 0) AS left_support, coalesce(pm.support, 0) AS right_support, CASE WHEN pm.support IS NULL THEN 'left' WHEN gm.support IS NULL THEN 'right' ELSE 'both' END AS side FROM gm FULL JOIN pm USING (pattern)"))(lambda spark, d: measures.overlap(*_pair(spark, d)))
query("overlap_counts", _both("SELECT CASE WHEN pm.support IS NULL THEN 'left' WHEN gm.support IS NULL THEN 'right' ELSE 'both' END AS side, count(*)::BIGINT AS patterns FROM gm FULL JOIN pm USING (pattern) GROUP BY 1"))(lambda spark, d: measures.overlap_counts(*_pair(spark, d)))


@query("superset_check", f"WITH gm AS (SELECT * FROM ({O.listing('priority', 1, 5, None)})), pm AS (SELECT * FROM ({_FREE_STRICT} {_ALL})) SELECT count(*)::BIGINT AS missing FROM pm WHERE pattern NOT IN (SELECT pattern FROM gm)")
def superset_check(spark: SparkSession, d: str) -> DataFrame:
    """Without a gap, growth finds all that the partner miner finds."""
    items = S.priority(spark, d)
    ours = growth.mine(items, "0.2", Options())
    return baselines.mine_partner(items, "0.2", 0.7).join(ours, "pattern", "left_anti").agg(F.count("*").alias("missing"))


@query("gap_lost", f"WITH a AS (SELECT * FROM ({O.listing('priority', 1, 2, None)})), b AS (SELECT * FROM ({O.listing('priority', 1, 2, 3)})) SELECT pattern, support FROM a WHERE pattern NOT IN (SELECT pattern FROM b)")
def gap_lost(spark: SparkSession, d: str) -> DataFrame:
    items = S.priority(spark, d)
    return plain(measures.lost_by_gap(growth.mine(items, "0.5", Options()), growth.mine(items, "0.5", Options(maxgap=3))))


@query("partner_missed", f"""WITH a AS (SELECT pattern, support, n_neg FROM ({O.mined('tags', 1, 2, 10)} SELECT * FROM m)), p AS (SELECT * FROM ({O.strict('tags', 1, 2, (7, 10))} {_ALL})),
k AS (SELECT * FROM ({O.listing('tags', 1, 250, None, ('x y z',))})) SELECT a.pattern, a.support::BIGINT AS support, coalesce(k.support, 0)::BIGINT AS partner_support FROM a LEFT JOIN k ON k.pattern = replace(a.pattern, '!', '') WHERE a.n_neg = 1 AND a.pattern NOT IN (SELECT pattern FROM p) AND coalesce(k.support, 0) < 88""")  # fmt: skip
def partner_missed(spark: SparkSession, d: str) -> DataFrame:
    """Patterns that growth finds and whose positive partner is rarer than the partner threshold, 70 % of half of the pages."""
    items = S.tags(spark, d)
    half = growth.threshold(growth.n_sequences(items), "0.5")
    return measures.missed_by_partner(growth.mine(items, half, Options(maxgap=10)), baselines.mine_partner(items, half, 0.7), growth.mine(items, 1, Options(negatives=False, max_itemsets=3)), growth.threshold(half, "0.7"))


# ---- after mining

_BRAND = O.mined("basket_brand", 2, 5, 3)
query("topk", f"{_BRAND} SELECT pattern, support::BIGINT AS support FROM m ORDER BY support DESC, pattern LIMIT 10")(lambda spark, d: postprocess.topk(plain(mined(spark, d, "basket_brand", "0.4", Options(maxgap=3))), 10))
query("endpoints", f"{O.mined('basket_brand', 143, 1000, 3)} SELECT pattern, support::BIGINT AS support FROM m WHERE pattern LIKE 'Brand#13 %Brand#13'")(lambda spark, d: plain(postprocess.endpoints(mined(spark, d, "basket_brand", "0.143", Options(maxgap=3)), "Brand#13", "Brand#13"), "n_pos >= 2"))
_EL = "list_transform(regexp_extract_all(pattern, '!?\\([^)]*\\)|!?`[^`]*`|!?[^\\s()`]+'), lambda e: e)"
_ABOVE = """l AS (SELECT pattern, support, regexp_extract_all(pattern, '!?\\([^)]*\\)|!?`[^`]*`|!?[^\\s()`]+') AS e FROM m),
s AS (SELECT pattern, support, list_filter(e, lambda x: x[1] <> '!') AS pos, list_transform(range(1, len(e)), lambda i: CASE WHEN e[i][1] = '!' THEN e[i][2:] WHEN e[i + 1][1] = '!' THEN NULL ELSE '' END) AS gap0 FROM l),
k AS (SELECT pattern, support, list_transform(pos, lambda x: regexp_extract_all(x, '`[^`]*`|[^\\s()`]+')) AS pos, list_transform(list_filter(gap0, lambda x: x IS NOT NULL), lambda x: regexp_extract_all(x, '`[^`]*`|[^\\s()`]+')) AS gap FROM s),
up AS (SELECT a.pattern AS p, a.support AS ps, b.support AS qs FROM k a JOIN k b ON a.pattern <> b.pattern AND len(a.pos) <= len(b.pos) AND a.pos[1:len(a.pos) - 1] = b.pos[1:len(a.pos) - 1]
 AND list_has_all(b.pos[len(a.pos)], a.pos[len(a.pos)]) AND len(list_filter(range(1, len(a.pos)), lambda i: NOT list_has_all(b.gap[i], a.gap[i]))) = 0)"""
_PRI = O.mined("priority", 1, 2, 3)
query("closed", f"{_PRI}, {_ABOVE} SELECT pattern, support::BIGINT AS support FROM m WHERE pattern NOT IN (SELECT p FROM up WHERE ps = qs)")(lambda spark, d: plain(postprocess.closed(mined(spark, d, "priority", "0.5", Options(maxgap=3)))))
query("maximal", f"{_PRI}, {_ABOVE} SELECT pattern, support::BIGINT AS support FROM m WHERE pattern NOT IN (SELECT p FROM up)")(lambda spark, d: plain(postprocess.maximal(mined(spark, d, "priority", "0.5", Options(maxgap=3)))))


_FOUR = f"""WITH {O.base('priority', 1, 5)}, a AS MATERIALIZED (SELECT a.sid, a.item AS x, b.item AS y, max(a.pos) AS p, b.pos AS e FROM w a JOIN w b ON {O.reach('a', 'b', None)} GROUP BY a.sid, a.item, b.item, b.pos),
z AS (SELECT sid, item AS z, max(pos) AS last FROM w GROUP BY 1, 2), b AS MATERIALIZED (SELECT a.sid, x, y, c.item AS z, max(a.e) AS p, c.pos AS e FROM a JOIN w c ON c.sid = a.sid AND c.pos > a.e GROUP BY a.sid, x, y, c.item, c.pos),
m AS (SELECT x, y, z, q.item AS q, 1 AS gap, count(DISTINCT a.sid) AS s FROM a JOIN z ON z.sid = a.sid AND last > e, f q WHERE NOT EXISTS (SELECT 1 FROM w i WHERE i.sid = a.sid AND i.pos > p AND i.pos < e AND i.item = q.item) GROUP BY x, y, z, q.item
UNION ALL SELECT x, y, z, q.item, 2, count(DISTINCT b.sid) FROM b, f q WHERE NOT EXISTS (SELECT 1 FROM w i WHERE i.sid = b.sid AND i.pos > p AND i.pos < e AND i.item = q.item) GROUP BY x, y, z, q.item),
k AS (SELECT * FROM m WHERE s >= (SELECT t FROM t))
SELECT {O.fmt('x')} || CASE gap WHEN 1 THEN ' !' || {O.fmt('q')} || ' ' || {O.fmt('y')} ELSE ' ' || {O.fmt('y')} || ' !' || {O.fmt('q')} END || ' ' || {O.fmt('z')} AS pattern, s::BIGINT AS support FROM k
WHERE NOT (gap = 1 AND q = y AND EXISTS (SELECT 1 FROM k o WHERE o.gap = 2 AND o.x = k.x AND o.y = k.y AND o.z = k.z AND o.q = k.y))"""


@query("merge_redundant", _FOUR)
def merge_redundant(spark: SparkSession, d: str) -> DataFrame:
    """Of the patterns of three items and an absence, mined without a gap."""
    found = mined(spark, d, "priority", "0.2", Options(max_items=4, max_pos_items=3))
    return plain(postprocess.merge_redundant(found.where("n_pos = 3 and n_neg = 1 and n_items = 4")))


SAME = ["click", "click error", "click !purchase error", "click !(purchase signup) error", "click !signup error", "click error signup", "click !signup error signup", "click signup"]
_SIDS = " UNION ALL ".join(f"SELECT '{p}' AS pattern, string_agg(sid, ',' ORDER BY sid) AS held FROM ({O.holders(parse(p))})" for p in SAME)
query("same_sids", f"WITH v AS ({O.VIEWS['days']}), h AS ({_SIDS}) SELECT pattern, min(pattern) OVER (PARTITION BY held) AS class, count(*) OVER (PARTITION BY held) AS members FROM h")(lambda spark, d: postprocess.same_sids(nested(spark, d, "days"), SAME))

CONTRASTED = ["the", "the !the of", "of !the the", "is !of the"]


def _contrast_sql() -> str:
    rows = []
    for p in CONTRASTED:
        e = parse(p)
        if len(e.positives) == 1:
            holds = f"SELECT DISTINCT sid FROM v WHERE item = '{e.positives[0][0]}'"
        else:
            holds = f"SELECT DISTINCT a.sid FROM v a JOIN v b ON {O.reach('a', 'b', 10)} WHERE a.item = '{e.positives[0][0]}' AND b.item = '{e.positives[1][0]}' AND NOT EXISTS (SELECT 1 FROM v m WHERE m.sid = a.sid AND m.pos > a.pos AND m.pos < b.pos AND m.item = '{e.absences[0][0]}')"
        rows.append(f"SELECT '{e.text}' AS pattern, count(*) FILTER (WHERE quality = 1 AND sid IN ({holds}))::BIGINT AS in_class, count(*) FILTER (WHERE quality = 0 AND sid IN ({holds}))::BIGINT AS out_class, count(*) FILTER (WHERE quality = 1) AS n1, count(*) FILTER (WHERE quality = 0) AS n0 FROM (SELECT DISTINCT sid FROM v) s JOIN labels ON doc_id = sid")
    return f"WITH v AS ({O.VIEWS['words']}) SELECT pattern, in_class, out_class, round((in_class * n0)::DOUBLE / nullif(out_class * n1, 0), 6) AS growth_rate FROM ({' UNION ALL '.join(rows)})"


query("contrast_quality", _contrast_sql())(lambda spark, d: postprocess.contrast_items(S.words(spark, d), S.load(spark, d, "labels").select(F.col("doc_id").alias("sid"), F.col("quality").alias("class")), CONTRASTED, 10))


def _switch_sql(view: str, pairs: list[tuple[str, str]], gap: int) -> str:
    out = []
    for x, y in pairs:
        at = f"FROM v a JOIN v b ON {O.reach('a', 'b', gap)} WHERE a.item = '{x}' AND b.item = '{x}'"
        out.append(f"SELECT '{x} {x}' AS pattern, count(DISTINCT a.sid)::BIGINT AS support {at}")
        out.append(f"SELECT '{x} {y} {x}' AS pattern, count(DISTINCT a.sid)::BIGINT AS support FROM v a JOIN v c ON {O.reach('a', 'c', gap)} JOIN v b ON {O.reach('c', 'b', gap)} WHERE a.item = '{x}' AND c.item = '{y}' AND b.item = '{x}'")
        out.append(f"SELECT '{x} !{y} {x}' AS pattern, count(DISTINCT a.sid)::BIGINT AS support {at} AND NOT EXISTS (SELECT 1 FROM v m WHERE m.sid = a.sid AND m.pos > a.pos AND m.pos < b.pos AND m.item = '{y}')")
    return f"WITH v AS ({O.VIEWS[view]}) " + " UNION ".join(out)


BRANDS = [("Brand#13", "Brand#11"), ("Brand#12", "Brand#25")]
query("switch_table", _switch_sql("status_items", [("NO", "RF"), ("RF", "AF")], 5))(lambda spark, d: plain(postprocess.switch(nested(spark, d, "status_items"), [("NO", "RF"), ("RF", "AF")], Constraints(5))))
query("case_switch", _switch_sql("basket_brand", BRANDS, 5))(lambda spark, d: plain(postprocess.switch(nested(spark, d, "basket_brand"), BRANDS, Constraints(5))))

# ---- experiments

GAPS = (3, 4, 7, 10, None)


def _sweep(view: str, sigmas: tuple[int, ...], gaps: tuple) -> str:
    return " UNION ALL ".join(f"SELECT {s}::INTEGER AS sigma, {g if g is not None else 0}::INTEGER AS maxgap, (SELECT count(*) FROM (SELECT * FROM ({O.mined(view, s, 100, g)} SELECT * FROM m) WHERE n_neg = 0))::BIGINT AS positives, (SELECT count(*) FROM (SELECT * FROM ({O.mined(view, s, 100, g)} SELECT * FROM m) WHERE n_neg > 0))::BIGINT AS negatives" for s in sigmas for g in gaps)


def sweep(spark: SparkSession, d: str, view: str, sigmas: tuple[int, ...], gaps: tuple, max_items: int = 3) -> DataFrame:
    """sigma, maxgap (0: none), positives, negatives of the growth miner."""
    items, out = S.VIEWS[view](spark, d), None
    for s in sigmas:
        for g in gaps:
            one = measures.counts(growth.mine(items, f"{s / 100:.2f}", Options(maxgap=g, max_items=max_items))).select(F.lit(s).alias("sigma"), F.lit(g or 0).alias("maxgap"), "positives", "negatives")
            out = one if out is None else out.unionAll(one)
    return out


query("gap_sweep", _sweep("priority", (40, 60), (4, 10, None)))(lambda spark, d: sweep(spark, d, "priority", (40, 60), (4, 10, None)))
query("rollup_sweep", f"SELECT sigma, maxgap, sum(negatives)::BIGINT AS negatives FROM ({_sweep('turns', (20, 40), (2, None))}) GROUP BY ROLLUP (sigma, maxgap)")(lambda spark, d: sweep(spark, d, "turns", (20, 40), (2, None)).rollup("sigma", "maxgap").agg(F.sum("negatives").alias("negatives")))
_PSWEEP = " UNION ALL ".join(f"SELECT {r}::INTEGER AS ratio, (SELECT count(*) FROM ({O.strict('priority', 1, 5, (r, 100))} SELECT * FROM m))::BIGINT AS positives, (SELECT count(*) FROM ({O.strict('priority', 1, 5, (r, 100))} SELECT * FROM g))::BIGINT AS negatives" for r in (100, 80, 20))


@query("partner_sweep", _PSWEEP)
def partner_sweep(spark: SparkSession, d: str) -> DataFrame:
    items, out = S.priority(spark, d), None
    for r in (100, 80, 20):
        one = measures.counts(baselines.mine_partner(items, "0.2", r / 100)).select(F.lit(r).alias("ratio"), "positives", "negatives")
        out = one if out is None else out.unionAll(one)
    return out


@query("memory_sweep", f"""WITH RECURSIVE z AS (SELECT 1), {O.base('priority', 1, 5)}, s AS (SELECT * FROM ({O.listing('priority', 1, 5, None, POSITIVE)})) SELECT 'partner' AS miner, sum(support)::BIGINT AS state_rows FROM s""".replace("WITH RECURSIVE z AS (SELECT 1), ", "WITH "))
def memory_sweep(spark: SparkSession, d: str) -> DataFrame:
    """Rows of state of the partner miner: the ids of all its positives."""
    found = growth.mine(S.priority(spark, d), "0.2", Options(negatives=False))
    return measures.partner_state(found).select(F.lit("partner").alias("miner"), "state_rows")


def _frontier(gap: int | None) -> str:
    """Rows of the two frontiers that three items need: the places of frequent items, and the ends of frequent pairs."""
    same, after = "b.sid = a.sid AND b.pos = a.pos AND b.item > a.item", O.reach("a", "b", gap)
    pairs = " UNION ALL ".join(f"SELECT sum(n) FROM (SELECT count(DISTINCT (a.sid, b.pos)) AS n FROM w a JOIN w b ON {on} GROUP BY a.item, b.item HAVING count(DISTINCT a.sid) >= (SELECT t FROM t))" for on in (same, after))
    base = O.base("priority", 1, 5)
    return f"SELECT * FROM (WITH {base} SELECT {gap or 0}::INTEGER AS maxgap, 1::INTEGER AS level, (SELECT count(*) FROM w)::BIGINT AS frontier_rows UNION ALL SELECT {gap or 0}, 2, (SELECT sum(x)::BIGINT FROM ({pairs}) y(x)))"


@query("memory_growth", " UNION ALL ".join(map(_frontier, (3, None))))
def memory_growth(spark: SparkSession, d: str) -> DataFrame:
    """Rows of the frontier per level, with and without a gap."""
    rows, items = [], S.priority(spark, d)
    for g in (3, None):
        m = growth.Miner(items, growth.threshold(growth.n_sequences(items), "0.2"), Options(maxgap=g))
        m.run()
        rows += [(g or 0, k, n) for k, n in enumerate(m.frontier_rows, 1)]
    return spark.createDataFrame(rows, "maxgap int, level int, frontier_rows long")


_LENGTH = " UNION ALL ".join(f"SELECT {n}::INTEGER AS length, count(*)::BIGINT AS patterns FROM ({O.listing('words', 1, 5, 3, where=f'pos <= {n}')})" for n in (20, 30, 60))


@query("length_effect", _LENGTH)
def length_effect(spark: SparkSession, d: str) -> DataFrame:
    items, out = S.words(spark, d), None
    for n in (20, 30, 60):
        one = growth.mine(S.first_n(items, n), "0.2", Options(maxgap=3)).agg(F.count("*").alias("patterns")).select(F.lit(n).alias("length"), "patterns")
        out = one if out is None else out.unionAll(one)
    return out


def _real_partner(items: DataFrame, sigma: str, large_alphabet: bool) -> DataFrame:
    """At a partner share of 70 %. Of a large alphabet only what may be frequent is packed."""
    if not large_alphabet:
        return baselines.mine_partner(items, sigma, 0.7)
    items, packed = bit_engine.thinned(items, low := lambda n: min(baselines.partner_thresholds(n, sigma, 0.7)))
    return baselines.mine_partner(items, sigma, 0.7, packed=packed, engine="bits" if bit_engine.fits(packed, low(packed.n)) else "auto")


#: Share, in percent, by view of the real data table: 5 % where the alphabet lets SQL follow; gap 10, three items here, five in the bench.
REAL = {"clicks": 5, "days": 5, "priority": 5, "turns": 5, "words": 20, "tags": 5, "basket_brand": 5}
for _view, _k in REAL.items():
    query(f"real_{_view}", O.listing(_view, _k, 100, 10))(lambda spark, d, v=_view, k=_k: plain(mined(spark, d, v, f"{k / 100}", Options(maxgap=10))))
    # without a gap, SQL follows the words at a higher share only
    _k = 50 if _view == "words" else _k
    query(f"real_partner_{_view}", f"{O.strict(_view, _k, 100, (7, 10))} {_ALL}")(lambda spark, d, v=_view, k=_k: plain(_real_partner(S.VIEWS[v](spark, d), f"{k / 100}", v == "words")))

_CASE = "pattern LIKE 'Brand#13 %' AND pattern LIKE '% Brand#13'"
#: Case A: 14.3 %, growth with gap 3, partner share a tenth.
_CASE_A = f"WITH a AS (SELECT pattern, support FROM ({O.listing('basket_brand', 143, 1000, 3)}) WHERE {{0}}), b AS (SELECT pattern, support::BIGINT AS support FROM ({O.strict('basket_brand', 143, 1000, (1, 10))} {_ALL}) WHERE {{0}}) "
_SIDES = "SELECT pattern, coalesce(a.support, 0) AS left_support, coalesce(b.support, 0) AS right_support, CASE WHEN b.support IS NULL THEN 'left' WHEN a.support IS NULL THEN 'right' ELSE 'both' END AS side FROM a FULL JOIN b USING (pattern)"


def _case(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    """Both miners, on sequences that are packed once."""
    items = S.basket_brand(spark, d)
    packed = bit_engine.pack(items)
    return growth.mine(items, "0.143", Options(maxgap=3), packed=packed), baselines.mine_partner(items, "0.143", 0.1, packed=packed)


def _case_ends(spark: SparkSession, d: str) -> DataFrame:
    """Patterns that begin and end with one item."""
    a, b = (x.where(_CASE.lower().replace("brand", "Brand")) for x in _case(spark, d))
    return measures.overlap(a, b)


query("case_endpoints", _CASE_A.format(_CASE) + _SIDES)(_case_ends)
query("case_overlap", _CASE_A.format("true") + f"SELECT side, count(*)::BIGINT AS patterns FROM ({_SIDES}) GROUP BY 1")(lambda spark, d: measures.overlap_counts(*_case(spark, d)))


@query("case_missed", f"""WITH a AS (SELECT pattern, support, n_neg FROM ({O.mined('basket_brand', 143, 1000, 3)} SELECT * FROM m)), p AS (SELECT * FROM ({O.strict('basket_brand', 143, 1000, (7, 10))} {_ALL})),
k AS (SELECT * FROM ({O.listing('basket_brand', 1, 10000, None, ('x y z',))})), t AS (WITH {O.base('basket_brand', 143, 1000)} SELECT (7 * t + 9) // 10 AS low FROM t)
SELECT a.pattern, a.support::BIGINT AS support, coalesce(k.support, 0)::BIGINT AS partner_support FROM a LEFT JOIN k ON k.pattern = replace(a.pattern, '!', ''), t WHERE a.n_neg = 1 AND a.pattern NOT IN (SELECT pattern FROM p) AND coalesce(k.support, 0) < low""")  # fmt: skip
def case_missed(spark: SparkSession, d: str) -> DataFrame:
    """What the partner miner misses because the partner is rarer than 70 % of the threshold (a tenth hides nothing here)."""
    items = S.basket_brand(spark, d)
    packed = bit_engine.pack(items)
    low = growth.threshold(growth.threshold(packed.n, "0.143"), "0.7")
    return measures.missed_by_partner(growth.mine(items, "0.143", Options(maxgap=3), packed=packed), baselines.mine_partner(items, "0.143", 0.7, packed=packed), growth.mine(items, 1, Options(negatives=False), packed=packed), low)


_SWITCHED = [t for x, y in BRANDS for t in (f"{x} {x}", f"{x} {y} {x}", f"{x} !{y} {x}")]


@query("case_switch_mined", f"SELECT * FROM ({O.listing('basket_brand', 12, 1000, 5, ('x y', 'x y z', 'x !q y'))}) WHERE pattern IN ({', '.join(map(repr, _SWITCHED))})")
def case_switch_mined(spark: SparkSession, d: str) -> DataFrame:
    """Case B as mined: 1.2 %, gap 5, the patterns of a switch and back among all that are found."""
    return plain(mined(spark, d, "basket_brand", "0.012", Options(maxgap=5))).where(F.col("pattern").isin(_SWITCHED))


# ---- the generated data sets

#: Seeds, mean lengths, shares in percent and gaps of the generated experiment. The bench runs it at five items.
SEEDS, LENGTHS, SHARES = (1, 2, 3), (20, 30), (10, 20)
for _seed in SEEDS:
    for _long in LENGTHS:
        O.VIEWS[f"synthetic_{_long}_{_seed}"] = O.synthetic(_seed, 500, _long)
O.VIEWS["synthetic_short"] = O.synthetic(1, 500, 20, pattern_len=3)


def synthetic(spark: SparkSession, seed: int, mean_len: int = 20, **kw) -> DataFrame:
    return S.exploded(generator.generate(spark, 500, mean_len, seed=seed, **kw)[0]).select("sid", "pos", "item")


query("synthetic_generate", O.VIEWS["synthetic_20_1"])(lambda spark, d: synthetic(spark, 1))


@query("synthetic_recovery", f"""WITH found AS (SELECT * FROM ({O.mined('synthetic_short', 1, 10, None)} SELECT * FROM m)), truth AS (SELECT unnest([{', '.join(repr(p.text) for p in generator.plan(20, 3, 3, 1))}]) AS pattern),
c AS (SELECT (SELECT count(*) FROM truth) AS planted, (SELECT count(*) FROM truth WHERE pattern IN (SELECT pattern FROM found)) AS hit, (SELECT count(*) FROM found WHERE n_neg > 0) AS mined)
SELECT planted, hit AS found_planted, round(hit / nullif(planted, 0), 6) AS recall, round(hit / nullif(mined, 0), 6) AS precision FROM c""")  # fmt: skip
def synthetic_recovery(spark: SparkSession, d: str) -> DataFrame:
    sequences, truth = generator.generate(spark, 500, n_patterns=3, pattern_len=3)
    return measures.recovery(truth, growth.mine(S.exploded(sequences), "0.1", Options(max_items=3)))


def synthetic_counts(spark: SparkSession, cells: list[tuple[int, int, int, int, int, int]]) -> DataFrame:
    """mean_len, seed, sigma (percent), maxgap (0: none), ratio (percent of the partner miner, 0: growth), patterns, of each cell (those, and the item limit).

    A data set of the experiment is small, so a task generates nothing: the rows of a seed are grouped and mined there, all cells of
    a data set in one task."""
    data = None
    for long, seed in sorted({(c[0], c[1]) for c in cells}):
        one = synthetic(spark, seed, long).select(F.lit(long).alias("mean_len"), F.lit(seed).alias("seed"), "sid", "pos", "item")
        data = one if data is None else data.unionAll(one)
    return data.groupBy("mean_len", "seed").applyInPandas(local_engine.counter(cells), local_engine.COUNTED)


def _synthetic_cells(miners: tuple[int, ...], gaps: tuple[int, ...], max_items: int = 3) -> list[tuple[int, int, int, int, int, int]]:
    return [(long, seed, share, gap, ratio, max_items) for long in LENGTHS for seed in SEEDS for share in SHARES for gap in gaps for ratio in miners]


def _counted(miner: Callable[[str, int], str], gaps: tuple[int, ...], ratio: int) -> str:
    return " UNION ALL ".join(f"SELECT {long}::INTEGER AS mean_len, {seed}::INTEGER AS seed, {share}::INTEGER AS sigma, {gap}::INTEGER AS maxgap, {ratio}::INTEGER AS ratio, (SELECT count(*) FROM ({miner(f'synthetic_{long}_{seed}', share, gap)}))::BIGINT AS patterns" for long in LENGTHS for seed in SEEDS for share in SHARES for gap in gaps)


def _growth_sql(view: str, share: int, gap: int) -> str:
    return O.listing(view, share, 100, gap or None)


def _partner_sql(ratio: int) -> Callable[[str, int, int], str]:
    return lambda view, share, gap: f"{O.strict(view, share, 100, (ratio, 100))} {_ALL}"


_KEYS = "mean_len, sigma, maxgap, ratio"
_FIVE = f"SELECT {_KEYS}, " + ", ".join(f"round(quantile_cont(patterns, {q}), 6) AS {n}" for q, n in ((0, "least"), (0.25, "low"), (0.5, "middle"), (0.75, "high"), (1, "most"))) + f" FROM ({{0}}) GROUP BY {_KEYS}"


def _five(spark: SparkSession, miners: tuple[int, ...], gaps: tuple[int, ...]) -> DataFrame:
    return measures.five_numbers(synthetic_counts(spark, _synthetic_cells(miners, gaps)).withColumn("patterns", F.col("patterns").cast("double")), "patterns", ["mean_len", "sigma", "maxgap", "ratio"])


#: Data sets of the gap sweep, on kinds: each third user, after so many events. Rows of one up to which a task mines it.
for _seed in SEEDS:
    for _long in LENGTHS:
        O.VIEWS[f"dealt_{_long}_{_seed}"] = f"SELECT * FROM ({O.VIEWS['kinds']}) WHERE pos <= {_long} AND sid % {len(SEEDS)} = {_seed - 1}"
TASK_ROWS = 100_000


def dealt_counts(items: DataFrame, cells: list[tuple[int, int, int, int, int, int]]) -> DataFrame:
    """As synthetic_counts, of the growth miner, on data sets dealt from given sequences. Large ones are mined on bits."""
    spark, seed = items.sparkSession, (F.pmod("sid", F.lit(len(SEEDS))) + 1).cast("int").alias("seed")
    first = written(S.first_n(items, max(LENGTHS)).select("sid", "pos", "item", seed))
    if (first.groupBy("seed").count().agg(F.max("count")).first()[0] or 0) <= TASK_ROWS:
        data = first.select(F.explode(F.array(*map(F.lit, LENGTHS))).alias("mean_len"), "seed", "sid", "pos", "item").where("pos <= mean_len")
        return data.groupBy("mean_len", "seed").applyInPandas(local_engine.counter(cells), local_engine.COUNTED)
    out, packed = [], {}
    for c in cells:
        long, of, sigma, gap, ratio, most = c
        part = first.where((F.col("seed") == of) & (F.col("pos") <= long)).select("sid", "pos", "item")
        if c[:2] not in packed:
            packed[c[:2]] = bit_engine.pack(part)
        found = growth.mine(part, f"{sigma / 100}", Options(maxgap=gap or None, max_items=most), engine="bits", packed=packed[c[:2]])
        out.append((long, of, sigma, gap, ratio, found.count()))
    return spark.createDataFrame(out, local_engine.COUNTED)


def _dealt_five(items: DataFrame, gaps: tuple[int, ...]) -> DataFrame:
    return measures.five_numbers(dealt_counts(items, _synthetic_cells((0,), gaps)).withColumn("patterns", F.col("patterns").cast("double")), "patterns", ["mean_len", "sigma", "maxgap", "ratio"])


query("synthetic_gap_sweep", _FIVE.format(_counted(lambda view, share, gap: _growth_sql(view.replace("synthetic", "dealt"), share, gap), (4, 10, 0), 0)))(lambda spark, d: _dealt_five(S.kinds(spark, d), (4, 10, 0)))
query("synthetic_partner_sweep", _FIVE.format(" UNION ALL ".join(_counted(_partner_sql(r), (0,), r) for r in (100, 70, 20))))(lambda spark, d: _five(spark, (100, 70, 20), (0,)))
query("synthetic_slope", f"SELECT mean_len, maxgap, round(regr_slope(ln(patterns), sigma), 6) AS slope FROM ({_counted(_growth_sql, (4, 0), 0)}) GROUP BY 1, 2")(lambda spark, d: measures.slope(synthetic_counts(spark, _synthetic_cells((0,), (4, 0))), "patterns", "sigma", ["mean_len", "maxgap"]))


O.VIEWS["basket_sample"] = f"SELECT * FROM ({O.VIEWS['basket_brand']}) WHERE ('0x' || substr(md5('0:' || sid), 1, 8))::BIGINT % 2 = 0"
_PAIRS_ONLY = ("x", "(x y)", "x y")
_ROUGH = O.mined("basket_sample", 1, 1, 3, _PAIRS_ONLY).replace("(n * 1 + 0) // 1 AS t", "greatest(1, floor((0.5 - sqrt(ln(2 / 0.01) / (2 * n))) * n))::BIGINT AS t")
query("sample_estimate", f"""WITH rough AS ({_ROUGH} SELECT pattern, round(support / n, 6) AS estimate FROM m, n), exact AS ({O.mined('basket_brand', 1, 2, 3, _PAIRS_ONLY)} SELECT pattern, support::BIGINT AS support, round(support / n, 6) AS rel_support FROM m, n)
SELECT pattern, estimate, support, rel_support FROM exact JOIN rough USING (pattern)""")(lambda spark, d: measures.two_phase(S.basket_brand(spark, d), nested(spark, d, "basket_brand"), 0.5, Options(maxgap=3, negatives=False, max_items=2), one_of=2))

# ---- operators on their own

_KV = f"WITH v AS ({O.VIEWS['kinds']})"


@query("gap_join", f"{_KV} SELECT a.item AS x, b.item AS y, count(*)::BIGINT AS n FROM v a JOIN v b ON {O.reach('a', 'b', 3)} GROUP BY 1, 2")
def gap_join(spark: SparkSession, d: str) -> DataFrame:
    v = S.kinds(spark, d)
    a, b = v.toDF("sid", "p", "x"), v.toDF("sid_", "q", "y")
    return a.join(b, (F.col("sid") == F.col("sid_")) & F.col("q").between(F.col("p") + 1, F.col("p") + 3)).groupBy("x", "y").agg(F.count("*").alias("n"))


@query("asof_last_before", f"WITH v AS ({O.VIEWS['clicks']}), y AS (SELECT * FROM v WHERE item = 'purchase'), x AS (SELECT * FROM v WHERE item = 'click') SELECT y.sid, y.pos, coalesce(x.pos, 0)::INTEGER AS last_click FROM y ASOF LEFT JOIN x ON y.sid = x.sid AND y.pos > x.pos")
def asof_last_before(spark: SparkSession, d: str) -> DataFrame:
    """The last click before each purchase (0: none), by a window."""
    from pyspark.sql import Window

    before = Window.partitionBy("sid").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    return S.clicks(spark, d).withColumn("last_click", F.last(F.when(F.col("item") == "click", F.col("pos")), ignorenulls=True).over(before)).where("item = 'purchase'").select("sid", "pos", F.coalesce("last_click", F.lit(0)).alias("last_click"))


@query("anti_window", f"WITH v AS ({O.VIEWS['clicks']}) SELECT sid, pos FROM v a WHERE item = 'click' AND NOT EXISTS (SELECT 1 FROM v b WHERE b.sid = a.sid AND b.pos BETWEEN a.pos + 1 AND a.pos + 3 AND b.item = 'error')")
def anti_window(spark: SparkSession, d: str) -> DataFrame:
    v = S.clicks(spark, d)
    a, b = v.where("item = 'click'").select("sid", "pos"), v.where("item = 'error'").select(F.col("sid").alias("s"), F.col("pos").alias("p"))
    return a.join(b, (F.col("sid") == F.col("s")) & F.col("p").between(F.col("pos") + 1, F.col("pos") + 3), "left_anti")


def _semi_items(items: DataFrame) -> DataFrame:
    frequent = growth.frequent_items(items, growth.threshold(growth.n_sequences(items), "0.2")).select("item")
    return items.join(small(frequent, frequent.count()), "item", "left_semi").select("sid", "pos", "item")


query("semi_items", f"WITH {O.base('words', 1, 5)} SELECT sid, pos, item FROM w")(lambda spark, d: _semi_items(S.words(spark, d)))


@query("window_gaps", f"WITH v AS ({O.VIEWS['priority']}) SELECT item, gap::INTEGER AS gap, count(*)::BIGINT AS n FROM (SELECT item, pos - lag(pos) OVER (PARTITION BY sid, item ORDER BY pos) AS gap FROM v) WHERE gap IS NOT NULL GROUP BY 1, 2")
def window_gaps(spark: SparkSession, d: str) -> DataFrame:
    from pyspark.sql import Window

    gap = F.col("pos") - F.lag("pos").over(Window.partitionBy("sid", "item").orderBy("pos"))
    return S.priority(spark, d).select("item", gap.alias("gap")).where("gap is not null").groupBy("item", "gap").agg(F.count("*").alias("n"))


@query("setops_sids", f"WITH v AS ({O.VIEWS['turns']}), a AS (SELECT DISTINCT sid FROM v WHERE item = 'system'), b AS (SELECT DISTINCT sid FROM v WHERE pos = 5) SELECT 'and' AS op, count(*)::BIGINT AS n FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'or', count(*) FROM (SELECT * FROM a UNION SELECT * FROM b) UNION ALL SELECT 'minus', count(*) FROM (SELECT * FROM a EXCEPT SELECT * FROM b)")
def setops_sids(spark: SparkSession, d: str) -> DataFrame:
    v = S.turns(spark, d)
    a, b = v.where("item = 'system'").select("sid").distinct(), v.where("pos = 5").select("sid").distinct()
    sizes = {"and": a.intersect(b), "or": a.union(b).distinct(), "minus": a.subtract(b)}
    out = None
    for op, df in sizes.items():
        one = df.agg(F.count("*").alias("n")).select(F.lit(op).alias("op"), "n")
        out = one if out is None else out.unionAll(one)
    return out


query("json_props", "SELECT (props->>'$.k')::INTEGER AS k, count(*)::BIGINT AS n FROM events GROUP BY 1")(lambda spark, d: S.load(spark, d, "events", "props").groupBy(F.get_json_object("props", "$.k").cast("int").alias("k")).agg(F.count("*").alias("n")))
query("date_buckets", "SELECT year(o_orderdate)::INTEGER AS year, month(o_orderdate)::INTEGER AS month, count(*)::BIGINT AS orders FROM orders GROUP BY 1, 2")(lambda spark, d: S.load(spark, d, "orders", "o_orderdate").groupBy(F.year("o_orderdate").alias("year"), F.month("o_orderdate").alias("month")).agg(F.count("*").alias("orders")))


query("last_n_days", f"SELECT sid, (pos - greatest(len - 3, 0))::INTEGER AS pos, item FROM (SELECT *, max(pos) OVER (PARTITION BY sid) AS len FROM ({O.VIEWS['days']})) WHERE pos > len - 3")(lambda spark, d: S.last_n(S.days(spark, d), 3))
query("drop_short", f"SELECT sid, pos, item FROM (SELECT *, max(pos) OVER (PARTITION BY sid) AS len FROM ({O.VIEWS['turns']})) WHERE len >= 4")(lambda spark, d: S.drop_short(S.turns(spark, d), 4))


@query("sessions_clicks", "SELECT sid, max(session) + 1 AS sessions FROM (SELECT sid, sum(CASE WHEN gap > 43200 THEN 1 ELSE 0 END) OVER (PARTITION BY sid ORDER BY seen ROWS UNBOUNDED PRECEDING)::BIGINT AS session FROM (SELECT user_id AS sid, ts AS seen, epoch(date_trunc('second', ts))::BIGINT - epoch(date_trunc('second', lag(ts) OVER (PARTITION BY user_id ORDER BY ts)))::BIGINT AS gap FROM events)) GROUP BY 1")
def sessions_clicks(spark: SparkSession, d: str) -> DataFrame:
    """Visits of a user, parted by half a day of silence."""
    rows = S.load(spark, d, "events", "user_id", "ts").select(F.col("user_id").alias("sid"), F.col("ts").alias("at"))
    return S.sessions(rows, "sid", "at", 43_200).groupBy("sid").agg((F.max("session") + 1).alias("sessions"))


@query("lookback_purchase", "WITH o AS (SELECT user_id AS sid, max(ts) AS last FROM events WHERE event_type = 'purchase' GROUP BY 1) SELECT user_id AS sid, event_type AS item, count(*)::BIGINT AS n FROM events JOIN o ON sid = user_id WHERE ts < last AND ts >= last - INTERVAL 7 DAY GROUP BY 1, 2")
def lookback_purchase(spark: SparkSession, d: str) -> DataFrame:
    """Events of the week before a user's last purchase."""
    events = S.load(spark, d, "events", "user_id", "ts", "event_type")
    outcome = events.where("event_type = 'purchase'").groupBy(F.col("user_id").alias("sid")).agg(F.max("ts").alias("outcome_at"))
    return S.lookback(events, "user_id", "ts", outcome, 7).groupBy(F.col("user_id").alias("sid"), F.col("event_type").alias("item")).agg(F.count("*").alias("n"))


query("bitmask_items", f"SELECT sid, bit_or(CASE item WHEN 'click' THEN 1 WHEN 'error' THEN 2 WHEN 'purchase' THEN 4 ELSE 8 END::BIGINT) AS mask FROM ({O.VIEWS['clicks']}) WHERE item IN ('click', 'error', 'purchase', 'signup') GROUP BY 1")(lambda spark, d: measures.item_masks(S.clicks(spark, d), ["click", "error", "purchase", "signup"]))
query("frontier_sizes", f"SELECT item, quantile_cont(n, 0.5)::DOUBLE AS middle FROM (SELECT item, sid, count(*) AS n FROM ({O.VIEWS['priority']}) GROUP BY 1, 2) GROUP BY 1")(lambda spark, d: measures.frontier_sizes(S.priority(spark, d), ["item"]))


@query("sql_recursive", f"WITH RECURSIVE v AS ({O.VIEWS['turns']}), walk AS (SELECT sid, pos, 1 AS k FROM v WHERE item = 'user' UNION ALL SELECT v.sid, v.pos, k + 1 FROM walk JOIN v ON v.sid = walk.sid AND v.pos = walk.pos + 1 WHERE v.item = CASE WHEN k % 2 = 1 THEN 'assistant' ELSE 'user' END AND k < 6) SELECT k::INTEGER AS k, count(*)::BIGINT AS n, count(DISTINCT sid)::BIGINT AS sequences FROM walk GROUP BY 1")
def sql_recursive(spark: SparkSession, d: str) -> DataFrame:
    """Unbroken exchanges by length, in recursive SQL over the registered views."""
    from .functions.surface import views

    views(S.turns(spark, d))
    return spark.sql("WITH RECURSIVE walk AS (SELECT sid, pos, 1 AS k FROM seq_items WHERE item = 'user' UNION ALL SELECT s.sid, s.pos, k + 1 FROM walk JOIN seq_items s ON s.sid = walk.sid AND s.pos = walk.pos + 1 WHERE s.item = CASE WHEN k % 2 = 1 THEN 'assistant' ELSE 'user' END AND k < 6) SELECT k, count(*) AS n, count(DISTINCT sid) AS sequences FROM walk GROUP BY k")


@query("item_rates", "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H') AS hour, event_type AS item, count(*)::BIGINT AS n FROM events GROUP BY 1, 2")
def item_rates(spark: SparkSession, d: str) -> DataFrame:
    """Events per item and hour; the same function serves a stream."""
    from .streaming import monitor

    events = S.load(spark, d, "events").select(F.col("ts").cast("timestamp").alias("at"), F.col("event_type").alias("item"))
    return monitor.item_rates(events, "1 hour").select(F.date_format("start", "yyyy-MM-dd HH").alias("hour"), "item", "n")


@query("udf_occurs", _support("days", "click !error click", GROWTH)[0])
def udf_occurs(spark: SparkSession, d: str) -> DataFrame:
    from .functions.surface import occurs_pattern

    holds = F.pandas_udf(occurs_pattern, "boolean")
    return nested(spark, d, "days").agg(F.sum(holds("itemsets", F.lit("click !error click")).cast("long")).alias("support")).select(F.lit("click !error click").alias("pattern"), "support")


@query("udtf_embeddings", f"""WITH v AS ({O.VIEWS['turns']}) SELECT a.sid, a.pos || ' ' || b.pos AS positions, NOT EXISTS (SELECT 1 FROM v m WHERE m.sid = a.sid AND m.pos > a.pos AND m.pos < b.pos AND m.item = 'assistant') AS ok FROM v a JOIN v b ON a.sid = b.sid AND a.pos < b.pos WHERE a.item = 'user' AND b.item = 'user'""")
def udtf_embeddings(spark: SparkSession, d: str) -> DataFrame:
    from .functions.surface import register

    register(spark)
    nested(spark, d, "turns").createOrReplaceTempView("negseq_turns")
    return spark.sql("SELECT sid, e.positions, e.ok FROM negseq_turns, LATERAL sequence_embeddings(itemsets, 'user !assistant user') e")


@query("seqtext_roundtrip", f"WITH v AS ({O.VIEWS['vec_labels']}) SELECT item, count(*)::BIGINT AS n, count(DISTINCT sid)::BIGINT AS sequences FROM v GROUP BY 1")
def seqtext_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    import uuid

    from .plans.stage import shared_dir
    from .sources import sequence_text

    path = f"{shared_dir(spark)}/seqtext-{uuid.uuid4().hex}"
    sequence_text.write(nested(spark, d, "vec_labels"), path)
    return S.exploded(sequence_text.read(spark, path)).groupBy("item").agg(F.count("*").alias("n"), F.count_distinct("sid").alias("sequences"))


_WATCHED = ["click !error purchase", "view signup"]
_STREAM = " UNION ".join(
    f"SELECT DISTINCT e1_0.sid, '{t}' AS pattern, strftime(e1_0.ts, '%Y-%m-%d %H:%M:%S.%f') AS at, e1_0.pos::BIGINT AS position FROM ({O.holders(parse(t), 5).replace('SELECT DISTINCT e0_0.sid', 'SELECT e1_0.*')}) e1_0" for t in _WATCHED
)


@query("stream_monitor", f"WITH v AS (SELECT DISTINCT user_id AS sid, dense_rank() OVER (PARTITION BY user_id ORDER BY ts) AS pos, event_type AS item, ts FROM events WHERE user_id IS NOT NULL AND ts IS NOT NULL AND event_type IS NOT NULL) {_STREAM}")
def stream_monitor(spark: SparkSession, d: str) -> DataFrame:
    """Completions of two patterns on the event stream, replayed in event time."""
    import uuid

    from .plans.stage import shared_dir
    from .streaming.monitor import replay

    events = S.load(spark, d, "events").select(F.col("user_id").alias("sid"), F.col("ts").cast("timestamp").alias("at"), F.col("event_type").alias("item"))
    done = replay(events, _WATCHED, Constraints(maxgap=5), path=f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}")
    return done.withColumn("at", F.date_format("at", "yyyy-MM-dd HH:mm:ss.SSSSSS"))
