import collections
import hashlib
import pathlib

import numpy as np
import pytest
from tokenizers import Tokenizer

import corpus_pipeline
from bandspark.llm import bpe, mixing, quality

SF = "/root/testdata/sf0.001"


def shingles(text, k):
    w = (text or "").encode().lower().split()
    return {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set())


def classes(docs, k, percent):
    """Smallest id reachable by links, by comparing all that share a shingle."""
    sets = {i: shingles(t, k) for i, t in docs.items()}
    by, parent = collections.defaultdict(list), {i: i for i in docs}

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in sorted(sets):
        near = collections.Counter(j for s in sets[i] for j in by[s])
        for j, n in near.items():
            if 100 * n >= percent * len(sets[i] | sets[j]):
                a, b = sorted((find(i), find(j)))
                parent[b] = a
        for s in sets[i]:
            by[s].append(i)
    return {i: find(i) for i in docs}


def test_stages_against_brute_force(spark):
    if not pathlib.Path(SF).exists():
        pytest.skip("no test tables")
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns = docs.columns
    texts = {r.doc_id: r.text for r in docs.collect()}
    verdicts = {r.doc_id: r.kept for r in quality.score_documents(docs).collect()}
    good = {i: t for i, t in texts.items() if verdicts[i]}
    df = corpus_pipeline.quality_stage(spark, docs, SF)
    assert {r.doc_id: r.text for r in df.collect()} == good and df.columns == columns
    last = {}
    for i, t in sorted(good.items()):
        last[t] = i
    unique = {i: t for t, i in last.items()}
    df = corpus_pipeline.exact_dedup_stage(spark, df, SF)
    assert {r.doc_id: r.text for r in df.collect()} == unique and df.columns == columns
    near = classes(unique, corpus_pipeline.SHINGLE_WORDS, corpus_pipeline.SIMILAR_PERCENT)
    single = {i: t for i, t in unique.items() if near[i] == i}
    assert len(single) < len(unique)
    df = corpus_pipeline.near_dedup_stage(spark, df, SF)
    assert {r.doc_id: r.text for r in df.collect()} == single and df.columns == columns
    taken = {r.doc_id: r.copies for r in mixing.mix_sources(df).collect()}
    df = corpus_pipeline.mixing_stage(spark, df, SF)
    assert collections.Counter(r.doc_id for r in df.collect()) == {i: n for i, n in taken.items() if n} and df.columns == columns
    library = Tokenizer.from_file(bpe.default_path())
    got = corpus_pipeline.run(spark, SF).collect()
    assert collections.Counter(r.doc_id for r in got) == {i: n for i, n in taken.items() if n}
    for r in got:
        ids = library.encode(single[r.doc_id], add_special_tokens=False).ids
        assert (r.n_tokens, r.ids_sha256) == (len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest())


def test_stages_take_odd_tables(spark):
    rows = [(None, None, None, None, 1), (1, "", "en", "s", 0), (2, "good words " * 60, None, None, 3), (2, "good words " * 60, None, None, 3), (3, " ".join(f"w{i} of text" for i in range(90)), "en", "t", 5)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, kept int")
    for table in (docs, docs.where("false")):
        out = table
        for _, stage in corpus_pipeline.STAGES:
            out = stage(spark, out, "nowhere")
        assert {r.doc_id for r in out.collect()} <= {3}
