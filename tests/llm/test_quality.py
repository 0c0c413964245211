import collections
import re

import numpy as np
import pytest

from bandspark.llm import quality
from bandspark.llm.textkit import string_buffer


def brute(t):
    t = t or ""
    w = re.findall(r"[^\x20\x09-\x0D]+", t)
    seen, dup = set(), 0
    for x in t.split("\n"):
        if re.search(r"[^\x20\x09-\x0D]", x):
            dup += x in seen
            seen.add(x)
    c = collections.Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
    cover = {i + d for i in range(len(w) - 2) if c[tuple(w[i : i + 3])] > 1 for d in range(3)}
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), dup, len(cover)


ODD = [None, "", "\n", "a\n\na\n a", "a b c a b c a", "x", "é é é é é é\né", "#|# <>", "l\nl\nl\r\nl", "a b\x0bc\x1cd", "日 本\n日 本\n\n", "a b c", "ends\n", "\nstarts\nstarts", "b c a b c"]


def test_statistics(spark):
    import pyarrow as pa

    for texts in (ODD, ODD[::-1], [t for t in ODD for _ in range(3)]):
        data, offsets = string_buffer(pa.array(texts, pa.string()))
        s = quality.statistics(data, offsets)
        got = list(zip(*[s[k].tolist() for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")], strict=True))
        assert got == [brute(t) for t in texts]
    docs = spark.createDataFrame([(i if i else None, t, True) for i, t in enumerate(ODD)], "doc_id long, text string, kept boolean")
    rows = quality.score_documents(docs).collect()
    assert len(rows) == len(ODD) and not any(r.kept for r in rows if r.base_failed)
    assert quality.score_documents(docs.where("false")).count() == 0 and quality.keep_good(docs.where("false")).columns == docs.columns


def drawn(share, n=200_000, rules=8, seed=3):
    """Vote patterns of documents with known shares and rates: (patterns, counts, rates by class, rule and vote)."""
    rng = np.random.default_rng(seed)
    good = rng.random(n) < share
    rates = np.array([[(0.5 + 0.04 * r, 0.1, 0.4 - 0.04 * r) for r in range(rules)], [(0.05, 0.1, 0.85)] * rules])
    cut = np.cumsum(rates, axis=2)[good.astype(int)]
    u = rng.random((n, rules, 1))
    votes = (u > cut[:, :, :2]).sum(axis=2) - 1
    patterns, counts = np.unique(votes, axis=0, return_counts=True)
    return patterns, counts, rates


@pytest.mark.parametrize("share", [0.3, 0.6, 0.95])
def test_fit_recovers_planted_shares_and_rates(share):
    patterns, counts, rates = drawn(share)
    model = quality.fit(patterns, counts)
    assert abs(model["share"] - share) < 0.02 and np.abs(model["rates"] - rates).max() < 0.02
    assert quality.posterior(patterns, model) @ counts / counts.sum() == pytest.approx(share, abs=0.02)


def test_prior_fades():
    patterns, counts, _ = drawn(0.3)
    far = [abs(quality.fit(patterns, counts * k)["share"] - quality.fit(patterns, counts * 10**6)["share"]) for k in (0.001, 1)]
    assert far[1] < 1e-3 and far[1] < far[0]


def plain_em(votes):
    """Document by document, in plain Python."""
    good, weight, rules = quality.PRIOR_GOOD_SHARE, quality.PRIOR_WEIGHT, len(votes[0])
    rates = [[list(p) for _ in range(rules)] for p in (quality.PRIOR_BAD, quality.PRIOR_GOOD)]

    def chance(v):
        both = [(1 - good), good]
        for k in (0, 1):
            for r, x in enumerate(v):
                both[k] *= rates[k][r]["-0+".index(x)]
        return both[1] / (both[0] + both[1])

    for _ in range(quality.ITERATIONS):
        post = [chance(v) for v in votes]
        before, good = good, (sum(post) + weight * quality.PRIOR_GOOD_SHARE) / (len(votes) + weight)
        for k, start in ((0, quality.PRIOR_BAD), (1, quality.PRIOR_GOOD)):
            for r in range(rules):
                seen = [weight * s for s in start]
                for v, p in zip(votes, post):
                    seen["-0+".index(v[r])] += p if k else 1 - p
                rates[k][r] = [x / sum(seen) for x in seen]
        if abs(good - before) < quality.TOLERANCE:
            break
    return [chance(v) for v in votes]


def test_keeps_clean_labelled_documents(spark):
    import pathlib

    sf = "/root/testdata/sf0.01"
    if not pathlib.Path(sf).exists():
        pytest.skip("no test tables")
    labels = spark.read.parquet(f"{sf}/labels.parquet").select("doc_id", "quality")
    every = quality.query(spark, sf).collect()
    for r, p in zip(every, plain_em([r.votes for r in every]), strict=True):
        assert r.p_good == pytest.approx(p, abs=1e-6) and r.kept == (not r.base_failed and p >= quality.THRESHOLD)
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()}
    assert all((r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == brute(texts[r.doc_id]) for r in every)
    rows = quality.query(spark, sf).join(labels, "doc_id").where("n_words >= 50").collect()
    assert all(r.kept for r in rows if r.quality == 1 and not r.base_failed)
    assert sum(r.kept for r in rows if r.quality == 0) <= 0.05 * sum(r.quality == 0 for r in rows)
