"""Secrets by a trigram inverted index.

Each rule's pattern gives a Boolean condition on trigrams (``trigrams.query_of``). Postings are built for the trigrams that
some rule asks for: a row per trigram and shard of the documents, with the sorted ids of that shard
(a shard holds about SHARD_DOCS ids whatever the corpus, so no list grows with it). A rule's condition is
answered by intersecting and joining those lists within each shard; only its candidates are matched against the
pattern. A rule without a mandatory trigram is matched against every text.

Built-in SQL functions only. Base kinds (always reported): assign (value of 12 characters or more), access (18 or more),
hex (16 or more). Added kinds: well-known token shapes and key headers.

Nulls and edges: null text is empty and has no spans; rows with a null id are candidates of every rule; repeated ids
are candidates together; other columns are ignored; places are code points; an empty table gives no rows.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bandspark.llm.spans import add_spans, joined
from bandspark.llm.trigrams import query_of, trigrams_of
from bandspark.session import materialize

_VALUE = "([A-Za-z0-9+/_.=-]+)"
#: The rules' patterns, base kinds first.
RULES = {
    "assign": rf"(?i:(password|passwd|secret|token|api_?key))[\"']?\x20*[:=]\x20*[\"']?{_VALUE}",
    "access": r"AKIA[A-Z0-9]{14,}+",
    "hex": r"(?<![0-9a-f])[0-9a-f]{16,}+",
    "hosting": r"gh[pousr]_[A-Za-z0-9]{36,}+",
    "chat": r"xox[abprs]-[A-Za-z0-9-]{10,}+",
    "webapi": r"AIza[0-9A-Za-z_-]{35}+",
    "signed": r"eyJ[A-Za-z0-9_-]{10,}+\.eyJ[A-Za-z0-9_-]{10,}+\.[A-Za-z0-9_-]++",
    "keyfile": r"-----BEGIN\x20(?:[A-Z]{2,10}\x20){0,2}PRIVATE\x20KEY-----",
}
BASE = ("assign", "access", "hex")
MIN_VALUE = 12
#: Documents of one shard of the postings, in the mean.
SHARD_DOCS = 4096


def build_postings(docs: DataFrame, trigrams: list[str], shard_docs: int = SHARD_DOCS) -> DataFrame:
    """shard, trigram, ids (sorted, distinct): the inverted index of those trigrams over lower-case texts."""
    shards = max(1, -(-docs.count() // shard_docs))
    text = F.lower(F.coalesce("text", F.lit("")))
    rows = docs.where("doc_id is not null").select("doc_id", text.alias("_text"))
    held = F.filter(F.array(*map(F.lit, trigrams)), lambda t: F.contains(F.col("_text"), t))
    rows = rows.select("doc_id", F.pmod(F.xxhash64("doc_id"), F.lit(shards)).alias("shard"), F.explode(held).alias("trigram"))
    return rows.groupBy("shard", "trigram").agg(F.sort_array(F.collect_set("doc_id")).alias("ids"))


def _answer(query, lists: Column) -> Column:
    """The ids that meet a condition, from the map trigram -> ids of one shard."""
    if isinstance(query, str):
        return F.coalesce(F.try_element_at(lists, F.lit(query)), F.array().cast("array<bigint>"))
    return reduce(F.array_intersect if query[0] == "and" else F.array_union, [_answer(q, lists) for q in query[1]])


def candidates(docs: DataFrame, rules: dict[str, str], shard_docs: int = SHARD_DOCS) -> DataFrame:
    """doc_id, rules (array of names): which documents each indexed rule has to look at."""
    queries = {k: q for k, p in rules.items() if (q := query_of(p)) is not True}
    wanted = sorted(set().union(*map(trigrams_of, queries.values())))
    postings = build_postings(docs, wanted, shard_docs)
    lists = postings.groupBy("shard").agg(F.map_from_entries(F.collect_list(F.struct("trigram", F.col("ids").cast("array<bigint>")))).alias("lists"))
    found = F.concat(*[F.transform(_answer(q, F.col("lists")), _tagged(k)) for k, q in queries.items()])
    return lists.select(F.explode(found).alias("c")).groupBy(F.col("c.id").alias("doc_id")).agg(F.collect_set("c.rule").alias("rules"))


def _tagged(rule: str):
    return lambda i: F.struct(i.alias("id"), F.lit(rule).alias("rule"))


def find_secrets(docs: DataFrame, rules: dict[str, str] | None = None, shard_docs: int = SHARD_DOCS) -> DataFrame:
    """doc_id and ``found``: an array of start, kind number, kind, end, value, in that order."""
    rules = rules or RULES
    scanned = [k for k, p in rules.items() if query_of(p) is True]
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("_text"))
    flagged = materialize(candidates(docs, rules, shard_docs).withColumnRenamed("doc_id", "_id"), "secret-candidates")
    rows = rows.join(flagged, F.col("doc_id") == F.col("_id"), "left")
    look = {k: F.lit(True) if k in scanned else F.col("doc_id").isNull() | F.coalesce(F.array_contains("rules", k), F.lit(False)) for k in rules}
    rows = add_spans(rows, "_text", {k: (p, look[k]) for k, p in rules.items()})
    found = F.concat(*[_numbered(k, n) for n, k in enumerate(rules)])
    return rows.select("doc_id", F.array_sort(found).alias("found"))


def _numbered(kind: str, n: int) -> Column:
    spans = F.col(f"_{kind}")
    if kind == "assign":
        spans = F.filter(spans, lambda s: F.length(F.regexp_extract(s["value"], RULES["assign"], 2)) >= MIN_VALUE)
    return F.transform(spans, lambda s: F.struct(s["start"].alias("start"), F.lit(n).alias("number"), F.lit(kind).alias("kind"), s["end"].alias("end"), s["value"].alias("value")))


def of_kind(found: Column, kind: str) -> Column:
    return F.filter(found, lambda s: s["kind"] == kind)


def query(spark, sf_dir: str) -> DataFrame:
    found = find_secrets(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    counts = [F.size(of_kind(F.col("found"), k)).cast("long").alias(f"n_{k}") for k in RULES]
    base = F.filter("found", lambda s: s["kind"].isin(*BASE))
    return found.select("doc_id", *counts, F.sha2(joined(base), 256).alias("base_sha256"), joined(F.col("found")).alias("spans"))
