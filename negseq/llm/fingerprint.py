"""Document fingerprints by one-permutation MinHash, in DataFrame functions only.

Each shingle of ``shingle`` words is hashed once; the high bits of the hash name its bin
and the least hash of each bin is kept. An empty bin borrows from the first filled bin
in a random order of its own, which is the same for all documents (optimal
densification). The low 8 bits of each bin are the fingerprint. Two fingerprints agree
by chance in 1 of 256 bins, which the likeness corrects.

Defined results: a null or blank text has no shingle and the empty fingerprint, which
is like another empty one (1) and like nothing else (0); fewer words than a shingle are
one shingle; rows of one id come in the order of their texts; a null id comes last.
Extra columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .shared import null_last

BITS = 8
BIN_BITS = 7
BINS = 1 << BIN_BITS
SPACES = " \t\n\x0b\f\r"


def with_shingles(df: DataFrame, text: str, out: str, shingle: int) -> DataFrame:
    """out: sorted hashes of the shingles."""
    words = F.split(F.btrim(F.col(text), F.lit(SPACES)), r"[\x20\x09-\x0D]+")
    df = df.withColumn("_h", F.transform(words, lambda w: F.xxhash64(w)))
    n = F.size("_h")
    rolled = F.transform("_h", lambda h, i: F.xxhash64(h, *(F.get("_h", i + j) for j in range(1, shingle))))
    kept = F.slice(rolled, 1, F.greatest(n - (shingle - 1), F.lit(1)))
    blank = F.btrim(F.col(text), F.lit(SPACES)) == ""
    return df.withColumn(out, F.sort_array(F.when(blank, F.slice(rolled, 1, 0)).otherwise(kept))).drop("_h")


def bin_of(x: Column) -> Column:
    return F.shiftright(x, 64 - BIN_BITS) + F.lit(BINS // 2)


def with_bins(df: DataFrame, hashes: str, out: str) -> DataFrame:
    """out: for each bin, in order, its number and the 8 bits kept, as one long; empty for no shingle."""
    low = lambda x: x.bitwiseAND(F.lit((1 << BITS) - 1))
    lead = F.filter(hashes, lambda x, i: (i == 0) | (bin_of(x) != bin_of(F.get(hashes, i - 1))))
    df = df.withColumn("_lead", lead)
    df = df.withColumn("_own", F.transform("_lead", lambda x: F.shiftleft(bin_of(x), BITS).bitwiseOR(low(x))))
    missing = F.array_except(F.sequence(F.lit(0).cast("long"), F.lit(BINS - 1).cast("long")), F.transform("_lead", bin_of))
    df = df.withColumn("_missing", missing)
    # the order in which bin b probes the others: by a hash of both numbers
    lent = lambda b: low(F.array_min(F.transform("_own", lambda e: F.shiftleft(F.xxhash64(b, F.shiftright(e, BITS)), BITS).bitwiseOR(low(e)))))
    borrowed = F.transform("_missing", lambda b: F.shiftleft(b, BITS).bitwiseOR(lent(b)))
    whole = F.when(F.size("_lead") == 0, F.col("_own")).when(F.size("_missing") == 0, F.col("_own")).otherwise(F.sort_array(F.concat("_own", borrowed)))
    return df.withColumn(out, whole).drop("_lead", "_own", "_missing", hashes)


def packed(bins: str) -> Column:
    """The low bits of all bins as hexadecimal text."""
    return F.array_join(F.transform(bins, lambda e: F.right(F.hex(e + F.lit(1 << 20)), F.lit(BITS // 4))), "")


def likeness(a: str, b: str) -> Column:
    share = F.size(F.array_intersect(a, b)) / F.lit(float(BINS))
    chance = 2.0**-BITS
    value = F.greatest(F.lit(0.0), (share - chance) / (1 - chance))
    return F.when((F.size(a) == 0) | (F.size(b) == 0), (F.size(a) == F.size(b)).cast("double")).otherwise(value)


def with_fingerprint(df: DataFrame, text: str, out: str, shingle: int = 5) -> DataFrame:
    return with_bins(with_shingles(df, text, "_hashes", shingle), "_hashes", out)


def fingerprints(docs: DataFrame, shingle: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, bins, fingerprint of every row."""
    rows = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    return with_fingerprint(rows, "text", "bins", shingle).select("doc_id", "bins", packed("bins").alias("fingerprint"))


def range_starts(ids: DataFrame, column: str, n: int) -> list[int]:
    """Ids at which about equal ranges begin, the least id first."""
    at = [i / n for i in range(1, n)]
    low, inner = ids.agg(F.min(column), F.percentile_approx(column, at, 10_000) if at else F.array()).first()
    return [] if low is None else sorted({low, *inner})


def range_of(column: Column, starts: list[int]) -> Column:
    """The number of the range that an id belongs to; two short searches instead of a long one."""
    step = max(1, int(len(starts) ** 0.5))
    groups = [starts[i : i + step] for i in range(0, len(starts), step)]
    upto = lambda own: F.size(F.filter(own, lambda s: s <= column))
    long_array = lambda xs: F.array(*(F.lit(x).cast("long") for x in xs))
    group = upto(long_array([g[0] for g in groups]))
    return (group - 1) * step + upto(F.element_at(F.array(*map(long_array, groups)), group)) - 1


def with_next(docs: DataFrame, starts: list[int], order: str, carried: list[str]) -> DataFrame:
    """Each row with next_<carried> of the row that follows in ascending order (the first row follows the last). The first rows of a range also visit the range before, so no window spans ranges."""
    n = len(starts)
    home = range_of(F.col(order), starts)
    first = F.element_at(F.array(*(F.lit(s).cast("long") for s in starts)), F.col("_range") + 1) == F.col(order)
    before = F.when(F.col("_range") == 0, n - 1).otherwise(F.col("_range") - 1)
    rows = docs.withColumn("_range", home).withColumn("_visits", F.when(first, F.array(F.struct(F.col("_range").alias("r"), F.lit(0).alias("guest")), F.struct(before.alias("r"), F.lit(1).alias("guest")))).otherwise(F.array(F.struct(F.col("_range").alias("r"), F.lit(0).alias("guest")))))
    rows = rows.withColumn("_visit", F.explode("_visits")).drop("_visits", "_range")
    by = Window.partitionBy("_visit.r").orderBy("_visit.guest", order, *carried[:1])
    rows = rows.select("*", *(F.lead(c).over(by).alias(f"next_{c}") for c in carried))
    return rows.where("_visit.guest = 0").drop("_visit")


def edited(docs: DataFrame, shingle: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Fingerprints of every text, of the text whose last half gives way to the start of the next document, and how alike they are."""
    n = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions", "200"))
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), null_last(F.col(id_col).cast("long")).alias("ord"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    starts = range_starts(rows.select("ord"), "ord", n)
    if not starts:
        return rows.select("doc_id", F.lit(0).cast("long").alias("n_chars"), *(F.lit("").alias(c) for c in ("edited_sha256", "fingerprint", "edited_fingerprint")), F.lit(0.0).alias("near_edited"), F.lit(0.0).alias("near_next")).limit(0)
    rows = with_next(with_fingerprint(rows, "text", "bins", shingle), starts, "ord", ["text", "bins"])
    n_chars = F.length("text")
    half = F.floor(n_chars / 2).cast("int")
    rows = rows.withColumn("edited", F.concat(F.substring("text", F.lit(1), n_chars - half), F.substring("next_text", F.lit(1), half))).drop("next_text")
    rows = rows.select("doc_id", n_chars.cast("long").alias("n_chars"), F.sha2("edited", 256).alias("edited_sha256"), "edited", "bins", "next_bins")
    rows = with_fingerprint(rows, "edited", "edited_bins", shingle)
    return rows.select("doc_id", "n_chars", "edited_sha256", packed("bins").alias("fingerprint"), packed("edited_bins").alias("edited_fingerprint"), likeness("bins", "edited_bins").alias("near_edited"), likeness("bins", "next_bins").alias("near_next"))
