"""Exact duplicates by composable polynomial fingerprints, confirmed by a chunkwise comparison.

The fingerprint of a byte string b is (sum b[j] * r**(n-1-j)) modulo 2**31 - 1 for two fixed bases r,
with the length. It composes: fingerprint(a + b) = fingerprint(a) * r**len(b) + fingerprint(b), so chunks
of one document are hashed on their own and combined. Documents up to ``parallel_above`` bytes are hashed
chunk by chunk in the task that reads them; longer ones are cut into chunk rows that are dealt over the
cluster, and their chunk hashes are combined per document.

Rows with equal (length, fingerprints) form a group. Each member of a group of two or more is compared with
the group's row of largest doc_id, chunk by chunk (chunk rows are joined on group and chunk number, which
Spark can split when one group is large); a member that differs somewhere (a hash collision) leaves the group
and is grouped by its SHA-256 instead.

Nulls and edges: null text counts as empty, and empty texts are equal to each other; a null doc_id is smaller
than any other; of repeated rows with the largest id one stays; other columns are ignored by the
fingerprints and carried through by ``drop_duplicates``; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from bandspark.llm.textkit import key_filter, small_batches, string_buffer, with_maybe
from bandspark.session import materialize

PRIME = (1 << 31) - 1
BASES = (1_103_515_245, 1_664_525_009)
CHUNK = 1 << 16
#: Code points of one chunk in the chunkwise comparison.
COMPARE_CHARS = 1 << 16
#: Bytes from which a document's chunks are hashed by different tasks.
PARALLEL_ABOVE = 8 << 20

_TABLES: dict[int, np.ndarray] = {}


def _powers(base: int) -> np.ndarray:
    """base ** (CHUNK - 1 - j) for j in a full chunk."""
    if base not in _TABLES:
        p, out = 1, np.empty(CHUNK, np.uint64)
        for j in range(CHUNK - 1, -1, -1):
            out[j] = p
            p = p * base % PRIME
        _TABLES[base] = out
    return _TABLES[base]


def chunk_fingerprint(data: np.ndarray, base: int) -> int:
    """Of at most CHUNK bytes: a byte times a 31-bit power, 2**16 of them, fits in 64 bits."""
    return int(np.dot(data.astype(np.uint64), _powers(base)[CHUNK - len(data) :])) % PRIME


def combine(left: tuple[int, int], right: tuple[int, int], base: int) -> tuple[int, int]:
    """(fingerprint, length) of the concatenation."""
    return (left[0] * pow(base, right[1], PRIME) + right[0]) % PRIME, left[1] + right[1]


def fingerprint(data: np.ndarray) -> tuple[int, int]:
    """Both fingerprints of a whole byte string, combined from its chunks."""
    out = []
    for base in BASES:
        whole = (0, 0)
        for at in range(0, len(data), CHUNK):
            piece = data[at : at + CHUNK]
            whole = combine(whole, (chunk_fingerprint(piece, base), len(piece)), base)
        out.append(whole[0])
    return out[0], out[1]


def _hash_batches(batches: Iterator[pa.RecordBatch], column: str) -> Iterator[pa.RecordBatch]:
    """Adds n_bytes, fp (both fingerprints in one long) and, where asked for, the digest."""
    for batch in small_batches(batches, column):
        data, offsets = string_buffer(batch.column(column))
        n = batch.num_rows
        fps, digests = np.empty(n, np.int64), []
        view = memoryview(data)
        for i in range(n):
            lo, hi = offsets[i], offsets[i + 1]
            a, b = fingerprint(data[lo:hi])
            fps[i] = a << 31 | b
            digests.append(hashlib.sha256(view[lo:hi]).hexdigest())
        yield pa.RecordBatch.from_arrays(
            [*batch.columns, pa.array(np.diff(offsets)), pa.array(fps), pa.array(digests, pa.string())], names=[*batch.schema.names, "n_bytes", "fp", "text_sha256"]
        )


def _chunk_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        data, offsets = string_buffer(batch.column("piece"))
        n = batch.num_rows
        cols = [np.empty(n, np.int64) for _ in range(4)]
        for i in range(n):
            lo, hi = int(offsets[i]), int(offsets[i + 1])
            for c, v in zip(cols, (*fingerprint(data[lo:hi]), *(pow(base, hi - lo, PRIME) for base in BASES)), strict=True):
                c[i] = v
        yield pa.RecordBatch.from_arrays([batch.column("_row"), batch.column("_no"), pa.array(np.diff(offsets)), *map(pa.array, cols)], names=["_row", "_no", "_len", "_a", "_b", "_pa", "_pb"])


def _combined(pieces: Column) -> Column:
    """Both fingerprints, in one long, of the chunks' (number, a, b, shifts for a and b): products of 31-bit numbers fit in 64 bits."""
    step = lambda acc, p, k: (acc[k] * p[f"_p{k}"] + p[f"_{k}"]) % PRIME
    zero = F.struct(F.lit(0).cast("long").alias("a"), F.lit(0).cast("long").alias("b"))
    return F.aggregate(F.array_sort(pieces), zero, lambda acc, p: F.struct(step(acc, p, "a").alias("a"), step(acc, p, "b").alias("b")), lambda acc: F.shiftleft(acc["a"], 31).bitwiseOR(acc["b"]))


def fingerprints(docs: DataFrame, with_text: bool = False, parallel_above: int = PARALLEL_ABOVE) -> DataFrame:
    """Per row: doc_id, n_bytes, fp, text_sha256 (and text)."""
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    schema = "doc_id {}, text string, n_bytes long, fp long, text_sha256 string".format(rows.schema["doc_id"].dataType.simpleString())
    large = F.octet_length("text") > parallel_above
    small = rows.where(~large).mapInArrow(lambda it: _hash_batches(it, "text"), schema)
    huge = rows.where(large).withColumn("_row", F.monotonically_increasing_id())
    step = COMPARE_CHARS // 4
    chunks = huge.select("_row", "text", F.explode(F.sequence(F.lit(0), F.floor((F.length("text") - 1) / step).cast("int"))).alias("_no")).select("_row", "_no", F.expr(f"substring(text, _no * {step} + 1, {step})").alias("piece"))
    hashed = chunks.repartition("_row", "_no").mapInArrow(_chunk_batches, "_row long, _no int, _len long, _a long, _b long, _pa long, _pb long")
    joined = _combined(F.collect_list(F.struct("_no", "_a", "_b", "_pa", "_pb")))  # a chunk's hashes only: 1/400 of its bytes
    whole = hashed.groupBy("_row").agg(F.sum("_len").alias("n_bytes"), joined.alias("fp"))
    huge = huge.join(whole, "_row").select("doc_id", "text", "n_bytes", "fp", F.sha2("text", 256).alias("text_sha256"))
    out = small.unionByName(huge)
    return out if with_text else out.drop("text")


def duplicate_groups(docs: DataFrame, parallel_above: int = PARALLEL_ABOVE) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256, _dup (which of equal rows it is)."""
    prints = materialize(fingerprints(docs, parallel_above=parallel_above), "exact-prints")
    key = ["n_bytes", "fp"]
    groups = materialize(prints.groupBy(*key).agg(F.max("doc_id").alias("_lead"), F.count("*").alias("_n")).where("_n > 1"), "exact-groups")
    # compare the texts of groups of two or more with the text of the group's leader, chunk by chunk
    hashed = F.xxhash64(*key)
    texts = with_maybe(fingerprints(docs, with_text=True, parallel_above=parallel_above), hashed, materialize(key_filter(groups, hashed), "exact-filter"))
    texts = texts.where("_maybe").join(groups, key)
    pieces = F.sequence(F.lit(0), F.floor(F.greatest(F.length("text") - 1, F.lit(0)) / COMPARE_CHARS).cast("int"))
    chunks = texts.select("doc_id", *key, "text_sha256", "_lead", "text", F.explode(pieces).alias("_no")).select(
        "doc_id", *key, "text_sha256", "_lead", "_no", F.expr(f"substring(text, _no * {COMPARE_CHARS} + 1, {COMPARE_CHARS})").alias("_piece")
    )
    chunks = materialize(chunks, "exact-chunks")
    # repeated rows of the leader itself: one set of chunks, the one of the smallest digest
    lead = chunks.where(F.col("doc_id").eqNullSafe(F.col("_lead"))).groupBy(*key, "_no").agg(F.min(F.struct("text_sha256", "_piece")).alias("_first"))
    lead = materialize(lead.select(*key, "_no", F.col("_first._piece").alias("_lead_piece")), "exact-leads")
    unlike = chunks.join(lead, [*key, "_no"]).where(F.col("_piece") != F.col("_lead_piece"))
    unlike = unlike.select(*key, "text_sha256").distinct().withColumn("_class", F.col("text_sha256"))
    classed = prints.join(materialize(unlike, "exact-unlike"), [*key, "text_sha256"], "left").withColumn("_class", F.coalesce("_class", F.lit("")))
    final = materialize(classed.groupBy(*key, "_class").agg(F.max("doc_id").alias("keep_id"), F.count("*").alias("group_size")), "exact-classes")
    out = classed.join(final, [*key, "_class"])
    lead_row = F.col("doc_id").eqNullSafe(F.col("keep_id"))
    one = Window.partitionBy("doc_id", "fp", "n_bytes", "_class").orderBy("doc_id")
    first = out.where(lead_row).withColumn("_dup", F.row_number().over(one) - 1)
    rest = out.where(~lead_row).withColumn("_dup", F.lit(1))
    cols = ["doc_id", "keep_id", F.col("group_size").cast("long").alias("group_size"), (F.col("_dup") == 0).alias("kept"), "text_sha256"]
    return first.unionByName(rest).select(*cols)


def drop_duplicates(docs: DataFrame) -> DataFrame:
    """The documents that stay, with all their columns. Only rows that may be on the list of dropped ones are joined with it."""
    cols = docs.columns
    rows = duplicate_groups(docs).groupBy(F.col("doc_id").alias("_id"), F.col("text_sha256").alias("_sha"))
    dropped = rows.agg(F.max("kept").alias("_some"), F.min("kept").alias("_all")).where("not _all").drop("_all")
    dropped = materialize(dropped, "exact-dropped")
    marked = with_maybe(docs, F.xxhash64("doc_id"), materialize(key_filter(dropped, F.xxhash64("_id")), "exact-filter"))
    clear = marked.where("not _maybe").select(*cols)
    marked = marked.where("_maybe").withColumn("_sha256", F.sha2(F.coalesce("text", F.lit("")), 256))
    same = F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("_sha256") == F.col("_sha"))
    whole = marked.join(dropped, same, "left_anti")
    repeated = marked.join(dropped.where("_some"), same, "left_semi")  # rows with the same id and text: one of them
    repeated = repeated.withColumn("_n", F.row_number().over(Window.partitionBy("doc_id", "_sha256").orderBy(F.lit(0)))).where("_n = 1")
    return clear.unionByName(whole.select(*cols)).unionByName(repeated.select(*cols))


ORACLE_SQL = """
SELECT doc_id, max(doc_id) OVER (PARTITION BY coalesce(text, '')) AS keep_id, count(*) OVER (PARTITION BY coalesce(text, '')) AS group_size,
       row_number() OVER (PARTITION BY coalesce(text, '') ORDER BY doc_id DESC NULLS LAST) = 1 AS kept, sha256(coalesce(text, '')) AS text_sha256
FROM documents
"""


def query(spark, sf_dir: str) -> DataFrame:
    return duplicate_groups(spark.read.parquet(f"{sf_dir}/documents.parquet"))
