"""Embedding near-duplicates: an exact metric range join around pivots.

Cosine at least c between unit vectors means a chord of at most r = sqrt(2 - 2c).
Pivots partition the vectors of a label in two tiers. *Balls* lie around pivots in dense
places: a vector within r of such a pivot belongs to the nearest one. What is in no ball
belongs to the *open cell* of its nearest spread pivot; there is one open cell for each
CELL of such vectors.

Cells are in order, balls first, and a pair of two cells meets in the earlier one, where
the vector of the later one is a guest. By the triangle inequality a vector x can be
within r of a member of pivot p's cell only if d(x, p) <= radius(p) + r, where radius(p) is
the largest distance of a member; for two open cells also only if x lies within r of
the bisector of both pivots. Balls are as narrow as r, so vectors in the open are guests of the few
balls that they nearly touch, and a vector costs little more than one copy.

By the same inequality the members of a ball within r / 2 of its pivot, its *core*, are
all linked. They are counted and not compared, so a hot group of copies is linear. What
is compared in a cell is each member with each vector outside the core, in blocks of
BLOCK by BLOCK vectors, so a task holds two blocks whatever the size of the cell.

Equal vectors collapse to one with a weight before the join. Of an open cell every pair is
compared: where vectors are far from all others in many dimensions no pivot can prune,
and a label with n such vectors ships n * n / BLOCK of them.

Defined results: a vector that is null, empty, zero or holds null or non-finite
components, and a null label, link with nothing; vectors of different lengths link with nothing;
rows of one id are one node of the graph but each counts as a vector of its own; extra columns are not read.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import components, written

#: Vectors of a block, and open vectors for which a label gets one open cell more.
BLOCK, CELL = 4096, 4096
#: Vectors that pivots are drawn from, and balls and open cells of a label, at most: the pivots that are broadcast are among the drawn.
PIVOT_ROWS, BALLS, OPEN_CELLS = 20_000, 256, 64
#: Number of the first open cell; balls have lower numbers.
OPEN = 1_000_000
#: Slack for rounding in the bounds of the join; the confirmation has none. Pairs of a core are this much closer than r.
SLACK, SURE = 1e-9, 1e-6
NONE = 2**63 - 1


def _unit(x: np.ndarray) -> np.ndarray:
    return x / np.linalg.norm(x, axis=-1, keepdims=True)


def _chord(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return np.sqrt(np.maximum(0, 2 - 2 * x @ y.T))


def _balls(x: np.ndarray, radius: float, most: int) -> tuple[np.ndarray, np.ndarray]:
    """Places of the pivots of dense places in a sample, those with most neighbours first, and which vectors no ball holds. A vector opens a ball if no ball holds it; balls of one vector are none."""
    chosen, free = [], np.ones(len(x), bool)
    for at in range(0, len(x), 512):
        near = _chord(x[at : at + 512], x) <= radius
        for i in np.flatnonzero(free[at : at + 512]):
            if not free[at + i]:
                continue
            own = near[i] & free
            if own.sum() > 1:
                chosen.append((int(own.sum()), at + int(i)))
                free &= ~own
    best = np.array([i for _, i in sorted(chosen, key=lambda c: (-c[0], c[1]))[:most]], int)
    return best, ~(_chord(x, x[best]) <= radius).any(1) if len(best) else np.ones(len(x), bool)


def _spread(x: np.ndarray, k: int) -> np.ndarray:
    """Farthest-first choice of k vectors."""
    chosen = [0]
    far = 1 - x @ x[0]
    while len(chosen) < min(k, len(x)):
        j = int(far.argmax())
        if far[j] < 1e-6:
            break
        chosen.append(j)
        far = np.minimum(far, 1 - x @ x[j])
    return x[chosen]


def _pivots(drawn: pd.DataFrame, share: float, radius: float) -> dict:
    """For each label and length: pivots of the balls, and of the open cells."""
    out = {}
    for key, own in drawn.groupby(["label", "size"]):
        x = _unit(np.stack(own["v"].to_numpy()).astype(np.float64))
        best, rest = _balls(x, radius, BALLS)
        cells = min(OPEN_CELLS, int(np.ceil(rest.sum() / share / CELL)))
        out[key] = (x[best], _spread(x[rest], cells) if cells > 1 else x[:0])
    return out


def _assign(pivots: dict, radius: float):
    """Own cell of each vector, and the earlier cells of which it may be a guest."""
    names = ["label", "size", "cell", "far", "home", "rep", "weight", "v"]

    def run(parts):
        for pdf in parts:
            out = []
            for (label, size), own in pdf.groupby(["label", "size"], sort=False):
                x = _unit(np.stack(own["v"].to_numpy()).astype(np.float64))
                balls, spread = pivots.get((label, size), (x[:0], x[:0]))
                row = np.arange(len(x))
                near, apart = _chord(x, balls), _chord(x, spread)
                inside = near.min(1) <= radius if len(balls) else np.zeros(len(x), bool)
                home = np.where(inside, near.argmin(1) if len(balls) else 0, OPEN + (apart.argmin(1) if len(spread) else 0))
                far = np.where(inside, near.min(1), apart.min(1) if len(spread) else 0.0) if len(balls) else apart.min(1) if len(spread) else np.zeros(len(x))
                cells = [(row, home, far, True)]
                if len(balls):
                    # a ball's radius is at most r; the join knows it better
                    i, j = np.nonzero((near <= 2 * radius + SLACK) & (np.arange(len(balls))[None, :] < home[:, None]))
                    cells.append((i, j, near[i, j], False))
                if len(spread):
                    own_cell = np.where(inside, 0, home - OPEN)
                    between = _chord(spread, spread)[own_cell]
                    gap = apart**2 - apart[row, own_cell][:, None] ** 2
                    reach = (gap <= 2 * between * radius + SLACK) & (np.arange(len(spread))[None, :] < own_cell[:, None]) & ~inside[:, None]
                    i, j = np.nonzero(reach)
                    cells.append((i, OPEN + j, apart[i, j], False))
                for i, cell, distance, is_home in cells:
                    if len(i):
                        part = own.iloc[i][["rep", "weight", "v"]].reset_index(drop=True)
                        out.append(part.assign(label=label, size=size, cell=cell.astype(np.int32), far=distance, home=is_home)[names])
            yield pd.concat(out, ignore_index=True) if out else pd.DataFrame(columns=names)

    return run


def _linked(a: np.ndarray, b: np.ndarray, cosine: float) -> np.ndarray:
    """Which pairs reach the cosine in double precision; pairs at the very threshold are computed one by one."""
    na, nb = np.linalg.norm(a, axis=1), np.linalg.norm(b, axis=1)
    cos = (a @ b.T) / na[:, None] / nb[None, :]
    link = cos >= cosine
    for i, j in zip(*np.nonzero(np.abs(cos - cosine) < 1e-12), strict=True):
        link[i, j] = float(np.dot(a[i], b[j])) / float(na[i] * nb[j]) >= cosine
    return link


def _block(cosine: float):
    """A block of a cell's members against a block of its vectors outside the core; links count for both sides, those of two members for the member."""

    def run(key, left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        if not len(left) or not len(right):
            return pd.DataFrame({"rep": [], "links": [], "low": []}).astype("int64")
        ia, ib = left["rep"].to_numpy(), right["_rep"].to_numpy()
        wa, wb = left["weight"].to_numpy(), right["_weight"].to_numpy()
        link = _linked(np.stack(left["v"].to_numpy()).astype(np.float64), np.stack(right["_v"].to_numpy()).astype(np.float64), cosine)
        link &= ia[:, None] != ib[None, :]
        # a member of the right side outside the core is on the left side too, where it counts its links with such members
        core = left["core"].to_numpy()
        once = np.where(right["_home"].to_numpy(), (wa * core) @ link, wa @ link)
        out = pd.DataFrame({"rep": np.r_[ia, ib], "links": np.r_[link @ wb, once], "low": NONE})
        return pd.concat([out[out["links"] > 0], _forest(link, ia, ib)], ignore_index=True).astype("int64")[["rep", "links", "low"]]

    return run


def _forest(link: np.ndarray, ia: np.ndarray, ib: np.ndarray) -> pd.DataFrame:
    """At most one edge for each vertex, which connect what the links connect: labels spread over the links until nothing changes."""
    big = len(ia)
    rows = np.arange(big)
    at, to = np.nonzero(link)
    while True:
        cols = np.full(len(ib), big)
        np.minimum.at(cols, to, rows[at])
        now = rows.copy()
        np.minimum.at(now, at, cols[to])
        if (now == rows).all():
            break
        rows = now
    hit, own = cols < big, rows != np.arange(big)
    return pd.DataFrame({"rep": np.r_[ib[hit], ia[own]], "links": 0, "low": np.r_[ia[cols[hit]], ia[rows[own]]]})


def cells(classes: DataFrame, cosine: float, pivot_rows: int = PIVOT_ROWS) -> DataFrame:
    """Members and guests of all cells: label, size, cell, far, home, core, rep, weight, v, and of each cell core_lead, core_weight, members, others (vectors outside the core)."""
    radius = float(np.sqrt(2 - 2 * cosine)) + SLACK
    total = classes.count()
    share = min(1.0, pivot_rows / max(total, 1))
    drawn = classes.where(F.pmod("rep", F.lit(2**30)) < int(share * 2**30)).select("label", "size", "v", "rep").orderBy("rep").limit(pivot_rows)
    pivots = _pivots(drawn.toPandas(), share, radius)
    kinds = "label long, size int, cell int, far double, home boolean, rep long, weight long, v array<double>"
    placed = written(classes.select("label", "size", "rep", "weight", "v").mapInPandas(_assign(pivots, radius), kinds), classes.sparkSession)
    placed = placed.withColumn("core", F.col("home") & (F.col("cell") < OPEN) & (F.col("far") <= radius / 2 - SURE))
    key = ["label", "size", "cell"]
    reach = placed.where("home").groupBy(*key).agg(F.max("far").alias("radius"), F.count("*").alias("members"), F.min(F.when(F.col("core"), F.col("rep"))).alias("core_lead"), F.sum(F.when(F.col("core"), F.col("weight"))).alias("core_weight"))
    known = placed.join(reach, key).where(f"home or far <= radius + {radius}")
    others = known.where("not core").groupBy(*key).agg(F.count("*").alias("others"))
    return known.join(others, key, "left").na.fill(0, ["others"])


def embedding_dedup(vectors: DataFrame, cosine: float = 0.93, id_col: str = "vec_id", vector_col: str = "embedding", label_col: str = "label", pivot_rows: int = PIVOT_ROWS) -> DataFrame:
    """One row per row of vectors: vec_id, n_links, component_id, kept. Pivots are drawn from at most pivot_rows vectors."""
    spark = vectors.sparkSession
    v = F.transform(F.col(vector_col), lambda x: x.cast("double"))
    sound = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))) & F.exists("v", lambda x: x != 0)
    rows = vectors.select(F.col(id_col).cast("long").alias("id"), v.alias("v"), F.col(label_col).cast("long").alias("label"))
    usable = rows.where(F.col("label").isNotNull() & F.col("id").isNotNull() & F.coalesce(sound, F.lit(False)))
    # equal vectors are one, with a weight
    classes = usable.groupBy("label", "v").agg(F.min("id").alias("lead"), F.count("*").alias("weight"))
    # the least id alone does not tell two classes apart when ids repeat
    classes = written(classes.select("label", "v", "lead", "weight", F.size("v").alias("size"), F.xxhash64("label", "v").alias("rep")), spark)
    placed = cells(classes, cosine, pivot_rows)
    blocks = lambda n: F.greatest(F.lit(1), F.ceil(F.col(n) / BLOCK)).cast("int")
    block = ["label", "size", "cell", "block", "other"]
    met = placed.where("others > 0")
    all_of = lambda n: F.explode(F.sequence(F.lit(0), blocks(n) - 1))
    dealt = lambda n: F.pmod(F.shiftright("rep", 7), blocks(n)).cast("int")
    left = met.where("home").withColumn("block", dealt("members")).withColumn("other", all_of("others")).select(*block, "rep", "weight", "v", "core")
    right = met.where("not core").withColumn("other", dealt("others")).withColumn("block", all_of("members"))
    right = right.select(*(F.col(c).alias(f"_{c}") for c in [*block, "rep", "weight", "v", "home"]))
    found = left.groupBy(*block).cogroup(right.groupBy(*(f"_{c}" for c in block))).applyInPandas(_block(cosine), "rep long, links long, low long")
    inner = placed.where("core").select("rep", (F.col("core_weight") - F.col("weight")).alias("links"), F.col("core_lead").alias("low"))
    found = written(found.unionAll(inner), spark)
    edges = found.where(f"low <> {NONE} and low <> rep").select(F.col("rep").alias("a"), F.col("low").alias("b"))
    sums = found.groupBy("rep").agg(F.sum("links").alias("links"))
    joined = components(classes.select(F.col("rep").alias("id")), edges)
    named = classes.join(joined, classes["rep"] == joined["id"], "left").drop("id").join(sums, "rep", "left")
    least = named.groupBy("component").agg(F.min("lead").alias("least"))
    named = named.join(least, "component").select("label", "v", "least", (F.coalesce("links", F.lit(0)) + F.col("weight") - 1).alias("n"))
    out = rows.join(named, ["label", "v"], "left")
    usable_row = F.col("least").isNotNull() & F.col("id").isNotNull()
    component = F.when(usable_row, F.col("least")).otherwise(F.col("id"))
    return out.select(F.col("id").alias("vec_id"), F.when(usable_row, F.col("n")).otherwise(F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(component == F.col("id"), F.lit(True)).alias("kept"))
