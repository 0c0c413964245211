"""Quality rules as weak supervision.

Every rule looks at a few exact statistics of a document and votes good (+1), bad (-1) or abstains (0).
``fit`` estimates, by expectation-maximisation over the counts of vote patterns, the share of good documents
and each rule's rates of voting good, bad and nothing among good and among bad documents. A Dirichlet prior of PRIOR_WEIGHT documents says that a rule
is better than chance; nothing else is held fixed. The rules are chosen so that every kind of junk meets two of them or more: a
rule's accuracy shows in its agreement with others. A document's posterior probability of being good replaces
"passes all rules". The counts are taken over all documents; what reaches the driver is one row per vote
pattern, at most 3 ** (number of rules).

Statistics per text: n_words, word_chars (code points in words), n_symbols (characters of ``#*$%&|<>``),
n_dup_lines (lines with a word that equal an earlier line), n_repeat_words (words in 3-word windows found twice
or more in the text, first included), n_upper (A-Z), n_digits (0-9), n_distinct (different words), n_plain (letters A-Z and a-z, digits, and code points
beyond ASCII), n_letter_words (words with a letter or such a code point).

Nulls and edges: null text is empty; a text without words fails the base rule; ids may be null or repeated; other
columns are ignored; an empty table gives no rows (and no fit is made).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from bandspark.llm.textkit import WHITE, blocks, mix, small_batches, string_buffer, word_hashes, word_spans
from bandspark.session import materialize

SYMBOLS = np.zeros(256, bool)
SYMBOLS[list(b"#*$%&|<>")] = True
LEAD = np.zeros(256, bool)  # first bytes of code points
LEAD[:0x80] = True
LEAD[0xC0:] = True
UPPER = np.zeros(256, bool)
UPPER[65:91] = True
DIGIT = np.zeros(256, bool)
DIGIT[48:58] = True
LETTER = np.zeros(256, bool)  # first bytes of code points beyond ASCII count as letters
LETTER[65:91] = LETTER[97:123] = LETTER[0xC0:] = True
STATS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_upper", "n_digits", "n_distinct", "n_plain", "n_letter_words")


def _per_row(flags: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    sums = np.zeros(len(flags) + 1, np.int64)
    np.cumsum(flags, out=sums[1:])
    return sums[offsets[1:]] - sums[offsets[:-1]]


def _repeats(keys: np.ndarray) -> np.ndarray:
    """True where a key occurs twice or more."""
    order = np.argsort(keys, kind="stable")
    s = keys[order]
    same = s[1:] == s[:-1]
    out = np.zeros(len(keys), bool)
    out[order[1:][same]] = True
    out[order[:-1][same]] = True
    return out


def _later_copies(keys: np.ndarray) -> np.ndarray:
    """True where a key occurred before."""
    out = np.ones(len(keys), bool)
    out[np.unique(keys, return_index=True)[1]] = False
    return out


def statistics(data: np.ndarray, offsets: np.ndarray) -> dict[str, np.ndarray]:
    """All STATS of the rows of one block."""
    n = len(offsets) - 1
    starts, ends, rows = word_spans(data, offsets)
    words = word_hashes(data, starts, ends, lower=False)
    counts = np.diff(rows)
    owner = np.repeat(np.arange(n, dtype=np.uint64), counts)
    salt = mix(owner + np.uint64(0x5851F42D4C957F2D))
    out = {"n_words": counts, "word_chars": _per_row(LEAD[data] & ~WHITE[data], offsets), "n_symbols": _per_row(SYMBOLS[data], offsets), "n_upper": _per_row(UPPER[data], offsets), "n_digits": _per_row(DIGIT[data], offsets)}
    letters = np.zeros(len(data) + 1, np.int64)
    np.cumsum(LETTER[data], out=letters[1:])
    out["n_plain"] = letters[offsets[1:]] - letters[offsets[:-1]] + out["n_digits"]
    out["n_letter_words"] = _per_row(letters[ends] > letters[starts], rows)
    out["n_distinct"] = np.bincount(owner[~_later_copies(words ^ salt)].astype(np.int64), minlength=n) if len(words) else np.zeros(n, np.int64)
    # 3-word windows inside one row, found twice or more in that row
    covered = np.zeros(len(words) + 1, np.int64)
    if len(words) >= 3:
        tri = mix(mix(mix(words[:-2]) * np.uint64(3) + words[1:-1]) * np.uint64(5) + words[2:])
        at = np.flatnonzero(owner[:-2] == owner[2:])
        at = at[_repeats((tri ^ salt[:-2])[at])]
        np.add.at(covered, at, 1)
        np.add.at(covered, at + 3, -1)
    out["n_repeat_words"] = _per_row((np.cumsum(covered)[:-1] > 0), rows)
    # lines with a word, equal to an earlier line of the row
    newline = np.flatnonzero(data == 10)
    lo = np.sort(np.concatenate([offsets[:-1], newline + 1]))  # a line starts after each newline, and at each row
    line_row = np.searchsorted(offsets[1:], lo, side="right")
    if len(newline):  # a line that starts where its row ends (or at the next row's start) is empty
        hi = np.sort(np.concatenate([offsets[1:], newline]))
    else:
        hi = offsets[1:]
    solid = (np.searchsorted(starts, hi) - np.searchsorted(starts, lo)) > 0
    lo, hi, line_row = lo[solid], hi[solid], line_row[solid]
    lines = word_hashes(data, lo, hi, lower=False) if len(lo) else np.zeros(0, np.uint64)
    later = _later_copies(lines ^ mix(line_row.astype(np.uint64) + np.uint64(0x14057B7EF767814F))) if len(lo) else np.zeros(0, bool)
    out["n_dup_lines"] = np.bincount(line_row[later], minlength=n) if len(lo) else np.zeros(n, np.int64)
    return out


def _stat_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Takes the text from the last column and puts its statistics there."""
    for batch in small_batches(batches, -1):
        data, offsets = string_buffer(batch.columns[-1])
        parts = [statistics(data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]) for a, b in blocks(offsets)]
        cols = [pa.array(np.concatenate([p[k] for p in parts]).astype(np.int64) if parts else [], pa.int64()) for k in STATS]
        yield pa.RecordBatch.from_arrays([*batch.columns[:-1], *cols], names=[*batch.schema.names[:-1], *STATS])


def document_statistics(docs: DataFrame, carry: dict[str, Column] | None = None) -> DataFrame:
    """STATS of every row, with the columns to carry (name: column), doc_id by default."""
    rows = docs.select(*[c.alias(k) for k, c in (carry or {"doc_id": F.col("doc_id")}).items()], F.col("text").alias("_text"))
    schema = T.StructType([*rows.schema.fields[:-1], *[T.StructField(k, T.LongType()) for k in STATS]])
    return rows.mapInArrow(_stat_batches, schema)


def _vote(bad: Column, good: Column) -> Column:
    return F.when(bad, F.lit(-1)).when(good, F.lit(1)).otherwise(F.lit(0))


def rules() -> dict[str, Column]:
    """name: vote, from the statistics' columns. Thresholds are those of public web-text filters; variety is the root type-token ratio."""
    w, c = F.greatest(F.col("n_words"), F.lit(1)), F.greatest(F.col("word_chars"), F.lit(1))
    mean, variety = F.col("word_chars") / w, F.col("n_distinct") / F.sqrt(w)
    return {
        "length": _vote(F.col("n_words") < 50, F.col("n_words") >= 80),
        "word_length": _vote((mean < 3) | (mean > 10), (mean >= 3.5) & (mean <= 8)),
        "symbols": _vote(F.col("n_symbols") > 0.1 * w, F.col("n_symbols") <= 0.01 * w),
        "repeats": _vote(F.col("n_repeat_words") > 0.3 * w, F.col("n_repeat_words") <= 0.1 * w),
        "lines": _vote((F.col("n_dup_lines") >= 5) & (F.col("n_dup_lines") * 20 > w), F.col("n_dup_lines") == 0),
        "upper": _vote(F.col("n_upper") > 0.4 * c, F.col("n_upper") <= 0.1 * c),
        "digits": _vote(F.col("n_digits") > 0.3 * c, F.col("n_digits") <= 0.05 * c),
        "variety": _vote(variety < 3, variety >= 5),
        "plain": _vote(F.col("n_plain") < 0.85 * c, F.col("n_plain") >= 0.9 * c),
        "words": _vote(F.col("n_letter_words") < 0.8 * w, F.col("n_letter_words") >= 0.9 * w),
    }


def base_failed() -> Column:
    return (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


#: A rule's votes (bad, nothing, good) among bad and among good documents before any data, as shares; the fit starts from them.
PRIOR_BAD = (0.3, 0.1, 0.6)
PRIOR_GOOD = (0.02, 0.1, 0.88)
PRIOR_GOOD_SHARE = 0.9
#: Documents that the prior counts as, whatever the number of documents: it fades as they grow.
PRIOR_WEIGHT = 20.0
ITERATIONS, TOLERANCE = 2000, 1e-9


def fit(patterns: np.ndarray, counts: np.ndarray, iterations: int = ITERATIONS) -> dict:
    """patterns: (P, R) votes in -1, 0, 1; counts: documents of each. The good documents' share and all rates (class, rule, vote), by expectation-maximisation."""
    counts = counts.astype(float)
    hot = np.stack([patterns == v for v in (-1, 0, 1)], axis=2).astype(float)  # P, R, 3
    prior = np.array([PRIOR_BAD, PRIOR_GOOD])[:, None, :] * np.ones((2, patterns.shape[1], 1))
    rates, share = prior.copy(), PRIOR_GOOD_SHARE
    for _ in range(iterations):
        post = posterior(patterns, {"rates": rates, "share": share})
        before, share = share, (counts @ post + PRIOR_WEIGHT * PRIOR_GOOD_SHARE) / (counts.sum() + PRIOR_WEIGHT)
        for k, p in ((0, 1 - post), (1, post)):
            seen = np.einsum("p,prv->rv", counts * p, hot) + PRIOR_WEIGHT * prior[k]
            rates[k] = seen / seen.sum(axis=1, keepdims=True)
        if abs(share - before) < TOLERANCE:
            break
    return {"rates": rates, "share": share}


def posterior(patterns: np.ndarray, model: dict) -> np.ndarray:
    """Probability of good for each pattern."""
    log = np.log(model["rates"])
    index = patterns + 1
    r = np.arange(patterns.shape[1])
    good = np.log(model["share"]) + log[1][r, index].sum(axis=1)
    bad = np.log(1 - model["share"]) + log[0][r, index].sum(axis=1)
    return 1 / (1 + np.exp(np.clip(bad - good, -700, 700)))


THRESHOLD = 0.5


def with_votes(stats: DataFrame) -> DataFrame:
    """Adds base_failed and votes, one of - 0 + for each rule."""
    signs = F.array(F.lit("-"), F.lit("0"), F.lit("+"))
    votes = F.concat(*[F.element_at(signs, v + 2) for v in rules().values()])
    return stats.withColumns({"base_failed": base_failed(), "votes": votes})


def fit_votes(voted: DataFrame) -> DataFrame | None:
    """(votes, p_good) of every vote pattern there is, at most 3 ** rules rows; None without documents."""
    found = voted.groupBy("votes").count().collect()  # bounded as said
    if not found:
        return None
    patterns = np.array([[" -0+".index(v) - 2 for v in r["votes"]] for r in found])
    p = posterior(patterns, fit(patterns, np.array([r["count"] for r in found])))
    return voted.sparkSession.createDataFrame([(r["votes"], float(x)) for r, x in zip(found, p, strict=True)], "votes string, p_good double")


def _decide(voted: DataFrame, table: DataFrame | None, threshold: float) -> DataFrame:
    if table is None:
        return voted.withColumns({"p_good": F.lit(0.0), "kept": F.lit(False)})
    return voted.join(F.broadcast(table), "votes", "left").withColumn("kept", ~F.col("base_failed") & (F.col("p_good") >= threshold))


def score_documents(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """One row per document: doc_id, STATS, base_failed, votes, p_good, kept."""
    voted = materialize(with_votes(document_statistics(docs)), "quality-votes")
    return _decide(voted, fit_votes(voted), threshold)


def keep_good(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """The rows kept, with all their columns: counted in one pass, decided in a second, without a join by id."""
    model = fit_votes(with_votes(document_statistics(docs)))
    carried = {f"_c{i}": F.col(f"`{c}`") for i, c in enumerate(docs.columns)}
    decided = _decide(with_votes(document_statistics(docs, carried)), model, threshold)
    return decided.where("kept").select(*[F.col(f"_c{i}").alias(c) for i, c in enumerate(docs.columns)])


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return score_documents(docs).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "p_good", "votes")
