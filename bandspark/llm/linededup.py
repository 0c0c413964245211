"""Repeated runs of lines, by a suffix array over line ids.

A text is the sequence of its lines (cut at newlines). A run of consecutive lines with MIN_WORDS words or more that occurred
before (in order of doc_id, then of text hash, then of line number; runs may overlap) is deleted; its first occurrence stays.

1. Lines that occur once cannot be in a repeated run: only lines with an equal elsewhere go on, ranked in order of hash.
2. Prefix doubling: the suffix at a line is ranked by its first 2**k lines, by sorting the pairs of ranks of its two halves.
   Only pairs that occur twice or more are ranked, so a suffix leaves when its longest common prefix with
   any other is shorter. The rows of equal rank are the LCP interval of depth 2**k.
3. Every line begins a shortest window with MIN_WORDS words, and ends one. A window of m lines is named by m and the ranks of
   its first and its last 2**k <= m lines; windows of one name are equal, that is, one LCP interval of depth m. A window that is
   not the first of its name is deleted. The windows deleted cover exactly the lines of all longer repeated runs:
   a line of such a run is in the window it ends, or, if the run has too few words up to it, in the one the run's first line begins.

Built-in SQL functions only. Nulls and edges: null text is one empty line; rows with the same id and text are one document
and share its decisions; a null id comes after all others; other columns are ignored by the decisions and carried by
``without_repeats``; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from bandspark.session import materialize

MIN_WORDS = 50
#: Values that may be broadcast in a join; rows of one part of a window.
MOST_HEAVY, PART_ROWS = 10_000, 250_000
WORD = r"[^\x20\x09-\x0D]+"
_LAST = (1 << 63) - 1
_DOC = ["d", "th"]


def _keys() -> list[Column]:
    text = F.coalesce("text", F.lit(""))
    return [F.coalesce(F.col("doc_id").cast("long"), F.lit(_LAST)).alias("d"), F.xxhash64(text).alias("th")]


def line_table(docs: DataFrame) -> DataFrame:
    """d, th (the document), line, h, h2 (96 bits of hash of the line), w (its words)."""
    lines = docs.select(*_keys(), F.posexplode(F.split(F.coalesce("text", F.lit("")), "\n", -1)).alias("line", "text"))
    return lines.select("d", "th", "line", F.xxhash64("text").alias("h"), F.hash("text").alias("h2"), F.regexp_count("text", F.lit(WORD)).alias("w"))


def rank_repeated(rows: DataFrame, by: list[str]) -> DataFrame:
    """(by..., n, rank) for the values that occur twice or more, n times; ranks follow the order of the values."""
    found = rows.groupBy(*by).agg(F.count("*").alias("n")).where("n > 1")
    ordered = found.repartitionByRange(*by).sortWithinPartitions(*by)
    return materialize(ordered.withColumn("rank", F.monotonically_increasing_id()), "line-ranks")


def by_value(rows: DataFrame, table: DataFrame, by: list[str]) -> DataFrame:
    """``rows`` joined with ``table`` (by..., n, more), n being the rows that each value has. Values with more than a MOST_HEAVY-th of all
    rows, fewer than MOST_HEAVY, are broadcast: no task gets all rows of one of them."""
    most = rows.count() // MOST_HEAVY
    more = [c for c in table.columns if c not in (*by, "n")]
    heavy = F.broadcast(table.where(F.col("n") > most).select(*by, *more, F.lit(True).alias("_heavy")))
    marked = rows.join(heavy, by, "left")
    rest = marked.where("_heavy is null").drop(*more, "_heavy").join(table.where(F.col("n") <= most).drop("n"), by)
    return marked.where("_heavy").drop("_heavy").unionByName(rest)


def spread(rows: DataFrame) -> DataFrame:
    """``rows`` of a written table by document, in as many parts as their number asks for (small rows pack well, so their bytes tell too little)."""
    parts = max(int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-rows.count() // PART_ROWS))
    return rows.repartition(parts, *_DOC)


def doubled(level: DataFrame, reach: int) -> DataFrame:
    """d, th, line, rank by twice as many lines: from the ranks by ``reach`` lines."""
    later = level.select("d", "th", (F.col("line") - reach).alias("line"), F.col("rank").alias("r2"))
    pairs = materialize(level.withColumnRenamed("rank", "r1").join(later, [*_DOC, "line"]), "line-pairs")
    return materialize(by_value(pairs, rank_repeated(pairs, ["r1", "r2"]), ["r1", "r2"]).select("d", "th", "line", "rank"), "line-level")


def shortest_windows(lines: DataFrame, min_words: int) -> DataFrame:
    """(d, th, line, m): the shortest window that each line begins, and that it ends, inside a stretch of repeated lines."""
    stretch = F.col("line") - F.row_number().over(Window.partitionBy(*_DOC).orderBy("line"))
    part = [*_DOC, "s"]
    rows = spread(lines).select(*_DOC, "line", "w", stretch.alias("s"))
    upto = F.sum("w").over(Window.partitionBy(*part).orderBy("line").rowsBetween(Window.unboundedPreceding, 0))
    rows = rows.withColumn("after", upto).withColumn("x", F.col("after") - F.col("w"))
    # boundaries: before each line, and after the stretch's last. A window goes from boundary to boundary.
    ends = rows.groupBy(*part).agg((F.max("line") + 1).alias("line"), F.max("after").alias("x"))
    spots = rows.select(*part, "line", "x").unionByName(ends)
    asked = spots.select(*part, F.col("x").cast("long").alias("x"), F.lit(0).alias("kind"), F.col("line").alias("spot"), F.lit(None).cast("int").alias("q"))
    asked = asked.unionByName(spots.select(*part, (F.col("x") + min_words).cast("long").alias("x"), F.lit(1).alias("kind"), F.lit(None).cast("int").alias("spot"), F.col("line").alias("q")))
    asked = asked.unionByName(spots.select(*part, (F.col("x") - min_words).cast("long").alias("x"), F.lit(2).alias("kind"), F.lit(None).cast("int").alias("spot"), F.col("line").alias("q")))
    asked = spread(materialize(asked, "line-spots"))
    running = lambda *order: Window.partitionBy(*part).orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    # the first boundary at or after x + min_words, in falling order; the last at or before x - min_words, in rising order
    ahead = asked.where("kind < 2").withColumn("to", F.last("spot", True).over(running(F.desc("x"), F.asc("kind"), F.desc("spot")))).where("kind = 1 and to is not null")
    back = asked.where("kind <> 1").withColumn("from", F.last("spot", True).over(running(F.asc("x"), F.asc("kind"), F.asc("spot")))).where("kind = 2 and from is not null")
    windows = ahead.select(*_DOC, F.col("q").alias("line"), (F.col("to") - F.col("q")).alias("m")).unionByName(back.select(*_DOC, F.col("from").alias("line"), (F.col("q") - F.col("from")).alias("m")))
    return materialize(windows.where("m > 0").distinct(), "line-windows")


def repeated_lines(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """(d, th, line, w) of the lines to delete."""
    lines = materialize(line_table(docs), "lines")
    level = by_value(lines, rank_repeated(lines, ["h", "h2"]), ["h", "h2"]).select(*_DOC, "line", "rank", "w").dropDuplicates([*_DOC, "line"])
    first = materialize(level, "line-level")
    windows = shortest_windows(first, min_words)
    longest = windows.agg(F.max("m")).first()[0] or 0
    named, level, reach = None, first.select(*_DOC, "line", "rank"), 1
    while reach <= longest:
        own = windows.where(f"m >= {reach} and m < {2 * reach}")
        tail = level.select(*_DOC, F.col("line").alias("at"), F.col("rank").alias("r2"))
        got = own.join(level.withColumnRenamed("rank", "r1"), [*_DOC, "line"]).withColumn("at", F.col("line") + F.col("m") - reach).join(tail, [*_DOC, "at"]).select(*_DOC, "line", "m", "r1", "r2")
        named = got if named is None else named.unionByName(got)
        if 2 * reach > longest:
            break
        level, reach = doubled(level, reach), 2 * reach
        if level.isEmpty():
            break
    if named is None:
        return first.where("false").select(*_DOC, "line", "w")
    named = materialize(named, "line-named")
    name = ["m", "r1", "r2"]
    begins = materialize(named.groupBy(*name).agg(F.min(F.struct(*_DOC, "line")).alias("first"), F.count("*").alias("n")).where("n > 1"), "line-firsts")
    later = by_value(named, begins, name).where(F.struct(*_DOC, "line") > F.col("first"))
    gone = later.select(*_DOC, F.explode(F.sequence(F.col("line"), F.col("line") + F.col("m") - 1)).alias("line")).distinct()
    return gone.join(first.select(*_DOC, "line", "w"), [*_DOC, "line"])


def deletions(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """One row per document with deletions: d, th, n_deleted, n_words_deleted, ranges (array of from, to; to exclusive)."""
    gone = materialize(repeated_lines(docs, min_words), "line-gone")
    island = F.col("line") - F.row_number().over(Window.partitionBy(*_DOC).orderBy("line"))
    runs = gone.withColumn("i", island).groupBy(*_DOC, "i").agg(F.min("line").alias("from"), (F.max("line") + 1).alias("to"), F.sum("w").alias("w"))
    return runs.groupBy(*_DOC).agg(F.sum(F.col("to") - F.col("from")).alias("n_deleted"), F.sum("w").alias("n_words_deleted"), F.array_sort(F.collect_list(F.struct("from", "to"))).alias("ranges"))


def without_repeats(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """The documents with all their columns, their texts without the deleted lines (null texts stay null)."""
    found = materialize(deletions(docs, min_words).select(*_DOC, "ranges"), "line-ranges")
    cols = docs.columns
    keyed = docs.withColumns(dict(zip(_DOC, _keys(), strict=True))) if not set(_DOC) & set(cols) else None
    if keyed is None:
        packed = docs.select(F.struct(*[F.col(f"`{c}`") for c in cols]).alias("doc"), *_keys())
    else:
        packed = keyed.select(F.struct(*[F.col(f"`{c}`") for c in cols]).alias("doc"), *_DOC)
    rows = packed.join(found, _DOC, "left")
    kept = F.filter(F.split(F.col("doc.text"), "\n", -1), lambda x, i: ~F.exists("ranges", lambda r: (i >= r["from"]) & (i < r["to"])))
    text = F.when(F.col("ranges").isNull(), F.col("doc.text")).otherwise(F.array_join(kept, "\n"))
    return rows.select(*[text.alias(c) if c == "text" else F.col(f"doc.`{c}`").alias(c) for c in cols])


def line_report(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """One row per document: doc_id, n_lines, n_deleted, n_words_deleted, deleted (from:to of each deleted run, comma-joined)."""
    found = materialize(deletions(docs, min_words), "line-ranges")
    rows = docs.select("doc_id", *_keys(), F.size(F.split(F.coalesce("text", F.lit("")), "\n", -1)).cast("long").alias("n_lines"))
    said = F.array_join(F.transform("ranges", lambda r: F.concat_ws(":", r["from"].cast("string"), r["to"].cast("string"))), ",")
    zero = lambda c: F.coalesce(F.col(c), F.lit(0)).cast("long").alias(c)
    return rows.join(found, _DOC, "left").select("doc_id", "n_lines", zero("n_deleted"), zero("n_words_deleted"), F.coalesce(said, F.lit("")).alias("deleted"))


ORACLE_SQL = f"""
WITH l AS (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS ls FROM documents),
u AS (SELECT doc_id, unnest(ls) AS t, generate_subscripts(ls, 1) - 1 AS i FROM l),
i AS (SELECT t, row_number() OVER () AS id, len(regexp_extract_all(t, '[^\\x20\\x09-\\x0D]+')) AS w FROM (SELECT DISTINCT t FROM u)),
p AS (SELECT u.doc_id, u.i, i.id, i.w, sum(i.w) OVER (PARTITION BY u.doc_id ORDER BY u.i) AS s FROM u JOIN i USING (t)),
a AS (SELECT doc_id, list(id ORDER BY i) AS ids, count(*) AS n FROM p GROUP BY doc_id),
f AS (SELECT x.doc_id, x.i AS b, (SELECT min(y.i) FROM p y WHERE y.doc_id = x.doc_id AND y.i >= x.i AND y.s >= x.s - x.w + {MIN_WORDS}) AS e FROM p x),
g AS (SELECT x.doc_id, (SELECT max(y.i) FROM p y WHERE y.doc_id = x.doc_id AND y.i <= x.i AND x.s - y.s + y.w >= {MIN_WORDS}) AS b, x.i AS e FROM p x),
v AS (SELECT DISTINCT * FROM (SELECT * FROM f UNION ALL SELECT * FROM g) WHERE b IS NOT NULL AND e IS NOT NULL),
k AS (SELECT v.doc_id, v.b, v.e, a.ids[v.b + 1:v.e + 1] AS r FROM v JOIN a USING (doc_id)),
o AS (SELECT doc_id, b, e, row_number() OVER (PARTITION BY r ORDER BY doc_id, b) AS no FROM k),
z AS (SELECT DISTINCT doc_id, unnest(range(b, e + 1)) AS i FROM o WHERE no > 1),
y AS (SELECT z.doc_id, z.i, p.w, z.i - row_number() OVER (PARTITION BY z.doc_id ORDER BY z.i) AS isl FROM z JOIN p ON p.doc_id = z.doc_id AND p.i = z.i),
q AS (SELECT doc_id, isl, min(i) AS lo, max(i) + 1 AS hi, sum(w) AS w FROM y GROUP BY 1, 2),
d AS (SELECT doc_id, sum(hi - lo) AS nd, sum(w) AS nw, string_agg(lo || ':' || hi, ',' ORDER BY lo) AS s FROM q GROUP BY 1)
SELECT a.doc_id, a.n AS n_lines, coalesce(d.nd, 0)::BIGINT AS n_deleted, coalesce(d.nw, 0)::BIGINT AS n_words_deleted, coalesce(d.s, '') AS deleted
FROM a LEFT JOIN d USING (doc_id)
"""


def query(spark, sf_dir: str) -> DataFrame:
    return line_report(spark.read.parquet(f"{sf_dir}/documents.parquet"))
