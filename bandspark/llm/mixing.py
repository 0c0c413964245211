"""Mixing sources to target weights by capped water-filling.

``mix_sources`` gives every source its weight's share of the words asked for, clamps a source at
``max_epochs`` times its own size, and gives the excess to the others in proportion to their weights
until no source is above its cap. The fixed point of that loop is one water level: the level at
which ``sum(min(cap, weight * level))`` meets the total, found over the per-source sums by sorting on
cap / weight. A document is then taken floor(target / size of its source) whole times, and a seeded
share of the documents once more: documents are ordered by the MD5 of seed, id and text, and taken until the
remaining words are met (the document at the edge is taken if that comes nearer).

No window holds a source: sums per prefix of that hash are cumulated (16 ** DIGITS rows a source and round) and the bucket in which the
remaining words end is cut finer until it holds at most EDGE_ROWS rows, or one hash. Rows of that one hash are equal rows; they are counted,
not ordered, and so many of them are taken as come nearest: their numbers are made per read split and shifted by the splits before.

Nulls and edges: null text has size 0; a null source is a source of its own, last in order; a null id
hashes as the empty string; repeated rows are taken one by one; an empty table gives no rows; a source
without words has target 0 and its documents are taken 0 words. Other columns are carried.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from bandspark.session import materialize

WORD = r"[^\x20\x09-\x0D]+"
WEIGHTS = (5, 2, 1)
MAX_EPOCHS = 3
SEED = "mix-2024"
#: Hex digits that a round cuts the edge bucket by, and rows of it that are ordered one by one.
DIGITS, EDGE_ROWS = 3, 100_000


def n_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = 1.0, max_epochs: int = MAX_EPOCHS) -> DataFrame:
    """sizes (source, size) to one row per source: source, source_size, target. Only per-source sums meet in a window."""
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    everything = Window.partitionBy()
    per = per.withColumn("_w", F.element_at(F.array(*map(F.lit, weights)), (F.pmod(F.row_number().over(by_name) - 1, F.lit(len(weights))) + 1).cast("int")).cast("long"))
    per = per.withColumn("_cap", F.col("source_size") * max_epochs).withColumn("_total", F.sum("source_size").over(everything) * F.lit(share))
    per = per.withColumn("_ratio", F.col("_cap").cast("double") / F.col("_w"))
    upto = Window.orderBy("_ratio", F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)
    # level if exactly the sources before this one are clamped
    level = (F.col("_total") - F.coalesce(F.sum("_cap").over(upto), F.lit(0))).cast("double") / (F.sum("_w").over(everything) - F.coalesce(F.sum("_w").over(upto), F.lit(0)))
    per = per.withColumn("_level", level)
    # the first source whose cap is at or above the level, and all after it, share that level
    per = per.withColumn("_water", F.min(F.when(F.col("_level") <= F.col("_ratio"), F.struct("_ratio", "_level"))).over(everything))
    target = F.when(F.col("_water").isNull() | (F.col("_ratio") < F.col("_water._ratio")), F.col("_cap").cast("double")).otherwise(F.least(F.col("_w") * F.col("_water._level"), F.col("_cap").cast("double")))
    return per.select("source", "source_size", target.alias("target"))


def _same(column: str, other: str) -> Column:
    return F.col(column).eqNullSafe(F.col(other))


def _upto(*order: str) -> Column:
    return F.sum("_sum").over(Window.partitionBy("source").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0))


def mix_plan(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = 1.0, max_epochs: int = MAX_EPOCHS, seed: str = SEED, edge_rows: int = EDGE_ROWS) -> DataFrame:
    """One row per source: source, source_size, target, _whole, and how far in hash order documents are taken once more:
    all before ``_edge``, and ``_some`` of the ``_equal`` rows at it."""
    sizes = materialize(docs.select("source", _hashed(seed).alias("_key"), n_words(F.col("text")).alias("size")), "mix-sizes")
    targets = source_targets(sizes, weights, share, max_epochs)
    targets = targets.withColumn("_whole", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("long"))
    targets = materialize(targets, "mix-targets")
    rest = F.col("target") - F.col("_whole") * F.col("source_size")
    # of each source the bucket in which its remaining words end: the last that starts before them
    edges = targets.select(F.col("source").alias("_s"), F.lit("").alias("_edge"), F.lit(0).cast("long").alias("_before"), rest.alias("_rest"))
    digits, near = 0, sizes.where("size > 0")
    while True:
        digits += DIGITS
        parts = near.join(edges, _same("source", "_s")).where(F.startswith("_key", "_edge"))
        sums = parts.groupBy("source", F.substring("_key", 1, digits).alias("_bucket")).agg(F.sum("size").alias("_sum"), F.count("*").alias("_n"), F.first("_before").alias("_b"), F.first("_rest").alias("_r"))
        sums = sums.withColumn("_upto", F.col("_b") + _upto("_bucket")).where(F.col("_upto") - F.col("_sum") < F.col("_r"))
        last = sums.groupBy("source").agg(F.max(F.struct("_bucket", "_sum", "_upto", "_r", "_n")).alias("_e"))
        edges = materialize(last.select(F.col("source").alias("_s"), F.col("_e._bucket").alias("_edge"), (F.col("_e._upto") - F.col("_e._sum")).alias("_before"), F.col("_e._r").alias("_rest"), F.col("_e._n").alias("_n")), "mix-edges")
        if digits >= 32 or (edges.agg(F.max("_n")).first()[0] or 0) <= edge_rows:
            break
        edges = edges.drop("_n")
    # rows of one hash are equal: so many of them as come nearest to the remaining words
    equal = near.join(edges, _same("source", "_s")).where(F.startswith("_key", "_edge")).groupBy("source", "_key").agg(F.sum("size").alias("_sum"), F.first("size").alias("_each"), F.first("_before").alias("_b"), F.first("_rest").alias("_r"))
    equal = equal.withColumn("_upto", F.col("_b") + _upto("_key")).where(F.col("_upto") - F.col("_sum") < F.col("_r"))
    at = equal.groupBy("source").agg(F.max(F.struct("_key", "_sum", "_each", "_upto", "_r")).alias("_e"))
    short = F.col("_e._r") - (F.col("_e._upto") - F.col("_e._sum"))  # words still missing before these rows
    low = F.floor(short / F.col("_e._each"))
    some = F.least(low + F.when((low + 1) * F.col("_e._each") - short <= short - low * F.col("_e._each"), 1).otherwise(0), F.floor(F.col("_e._sum") / F.col("_e._each")))
    at = at.select(F.col("source").alias("_s"), F.col("_e._key").alias("_edge"), some.cast("long").alias("_some"), F.floor(F.col("_e._sum") / F.col("_e._each")).alias("_equal"))
    return materialize(targets.join(at, _same("source", "_s"), "left").select("source", "source_size", "target", "_whole", "_edge", "_some", "_equal"), "mix-plan")


def _hashed(seed: str) -> Column:
    return F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.lit(":"), F.coalesce("text", F.lit(""))))


def _numbered(rows: DataFrame) -> DataFrame:
    """Adds ``_no``, from 0 per source, to rows of a written table: numbers in each read split, after those of the splits before."""
    at = materialize(rows.withColumn("_row", F.monotonically_increasing_id()), "mix-equal").withColumn("_part", F.shiftright("_row", 33))
    own = F.row_number().over(Window.partitionBy("_source", "_part").orderBy("_row")) - 1
    before = F.sum("count").over(Window.partitionBy("_source").orderBy("_part").rowsBetween(Window.unboundedPreceding, -1))
    shifts = at.groupBy("_source", "_part").count().select(F.col("_source").alias("_t"), F.col("_part").alias("_p"), F.coalesce(before, F.lit(0)).alias("_shift"))
    return at.withColumn("_in", own).join(shifts, _same("_source", "_t") & (F.col("_part") == F.col("_p"))).withColumn("_no", F.col("_in") + F.col("_shift")).drop("_row", "_part", "_in", "_t", "_p", "_shift")


def mix_sources(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, share: float = 1.0, max_epochs: int = MAX_EPOCHS, seed: str = SEED, edge_rows: int = EDGE_ROWS) -> DataFrame:
    """The rows of ``docs`` with all their columns in the struct ``doc``, and doc_id, size, source_size, target, copies, taken (words, repeats counted)."""
    plan = mix_plan(docs, weights, share, max_epochs, seed, edge_rows).withColumnRenamed("source", "_source")
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("doc"), "source", "doc_id", n_words(F.col("text")).alias("size"), _hashed(seed).alias("_key"))
    rows = rows.join(plan, _same("source", "_source")).drop("source")
    first = (F.col("_key") < F.col("_edge")) | ((F.col("_key") == F.col("_edge")) & (F.col("_some") > 0))
    every = rows.withColumn("_once", F.coalesce(first, F.lit(False)))
    if not plan.where("_some > 0 and _some < _equal").isEmpty():  # some, not all, of equal rows are taken
        split = F.coalesce((F.col("_key") == F.col("_edge")) & (F.col("_some") < F.col("_equal")), F.lit(False))
        cut = _numbered(rows.where(split)).withColumn("_once", F.col("_no") < F.col("_some")).drop("_no")
        every = every.where(~split).unionByName(cut)
    copies = F.least(F.col("_whole") + F.col("_once").cast("long"), F.lit(max_epochs).cast("long"))
    return every.select("doc", "doc_id", "size", "source_size", "target", copies.alias("copies"), (copies * F.col("size")).alias("taken"))


def mixed_documents(docs: DataFrame, **options) -> DataFrame:
    """The mix itself: every document as many times as it is taken, in the columns of ``docs``."""
    mixed = mix_sources(docs, **options).where("copies > 0")
    return mixed.select("doc", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))).alias("_copy")).select("doc.*")


ORACLE_SQL = f"""
WITH s AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+'))::BIGINT AS size,
                  md5(concat('{SEED}:', coalesce(doc_id::VARCHAR, ''), ':', coalesce(text, ''))) AS k FROM documents),
p AS (SELECT source, sum(size)::BIGINT AS source_size FROM s GROUP BY source),
w AS (SELECT *, CASE (row_number() OVER (ORDER BY source COLLATE "C" NULLS LAST) - 1) % 3 WHEN 0 THEN 5 WHEN 1 THEN 2 ELSE 1 END AS wt FROM p),
r AS (SELECT *, 3 * source_size AS cap, (3 * source_size)::DOUBLE / wt AS ratio FROM w),
l AS (SELECT *, ((sum(source_size) OVER ())::DOUBLE - coalesce(sum(cap) OVER before, 0)::DOUBLE) / (sum(wt) OVER () - coalesce(sum(wt) OVER before, 0))::DOUBLE AS lvl
      FROM r WINDOW before AS (ORDER BY ratio, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
f AS (SELECT ratio AS fr, lvl AS fl FROM l WHERE lvl <= ratio ORDER BY ratio, lvl LIMIT 1),
t AS (SELECT source, source_size, CASE WHEN fr IS NULL OR ratio < fr THEN cap::DOUBLE ELSE least(wt * fl, cap::DOUBLE) END AS target
      FROM l LEFT JOIN f ON true),
q AS (SELECT *, CASE WHEN source_size > 0 THEN floor(target / source_size)::BIGINT ELSE 0 END AS whole FROM t),
z AS (SELECT *, target - whole * source_size AS rest FROM q),
c AS (SELECT s.doc_id, s.size, z.source_size, z.target, z.whole, z.rest,
             sum(s.size) OVER (PARTITION BY s.source ORDER BY s.k ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS reach
      FROM s JOIN z ON s.source IS NOT DISTINCT FROM z.source)
SELECT doc_id, size, source_size, target,
       least(3, whole + CASE WHEN reach < rest OR (reach - size < rest AND reach - rest <= rest - (reach - size)) THEN 1 ELSE 0 END) * size AS taken
FROM c
"""


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return mix_sources(docs).select("doc_id", "size", "source_size", "target", "taken")
