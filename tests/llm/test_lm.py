import collections
import math
import pathlib
import zlib

import numpy as np
import pytest

from bandspark.llm import lm
from bandspark.llm.gru import Gru


def tokens(text):
    return (text or "").encode().lower().split() + [None]


def base_scores(rows):
    train = [t for i, t in rows if zlib.crc32(str(i).encode() if i is not None else b"") % 7 != 2]
    c = collections.Counter(x for t in train for x in tokens(t))
    n, v = sum(c.values()), len(c)
    return n, {i: (len(tokens(t)), sum(c[x] > 0 for x in tokens(t)), sum(math.log10((c[x] + 1) / (n + v + 1)) for x in tokens(t))) for i, t in rows}


def test_table_against_brute_force_and_held_out_gain(spark):
    sf = "/root/testdata/sf0.01"
    if not pathlib.Path(sf).exists():
        pytest.skip("no test tables")
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()]
    n, want = base_scores(rows)
    got = lm.query(spark, sf).collect()
    assert len(got) == len(rows)
    for r in got:
        assert (r.n_tokens, r.n_known, r.train_tokens) == (*want[r.doc_id][:2], n)
        assert r.base_score == pytest.approx(want[r.doc_id][2], rel=1e-9)
        assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 7 == 2) and r.score < 0
    held = [r for r in got if r.held_out]
    assert sum(r.score for r in held) > sum(r.base_score for r in held)


def test_edges(spark):
    rows = [(1, "a b A"), (2, None), (3, ""), (3, "a"), (3, "a"), (None, "b c")] + [(100 + i, "the cat sat on the mat") for i in range(20)]
    docs = spark.createDataFrame([(*r, 1) for r in rows], "doc_id long, text string, score int")
    got = lm.score_documents(docs, block_tokens=20).collect()
    assert len(got) == len(rows) and all(math.isfinite(r.score) for r in got)
    assert sorted(r.n_tokens for r in got if r.doc_id == 3) == [1, 2, 2] and [r.n_tokens for r in got if r.doc_id is None] == [3]
    assert lm.score_documents(docs.where("false")).count() == 0
    held = next(i for i in range(100) if zlib.crc32(str(i).encode()) % 7 == 2)
    (alone,) = lm.score_documents(spark.createDataFrame([(held, "x y")], "doc_id long, text string")).collect()
    assert (alone.train_tokens, alone.n_known, alone.score) == (0, 0, alone.base_score)


def test_every_training_document_is_learnt_from_once(spark, monkeypatch):
    rows = [(i, f"the cat {i % 9} sat on mat {i}") for i in range(200)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(40)
    met, average = [], lm._average
    monkeypatch.setattr(lm, "_average", lambda trained, *a: met.extend(trained.select("key", "w").collect()) or average(trained, *a))
    got = lm.score_documents(docs, block_tokens=40).collect()
    assert len(met) == len({r.key for r in met}) > 30
    assert sum(r.w for r in met) == got[0].train_tokens


def test_frequent_words_grow_with_the_vocabulary(spark):
    docs = spark.createDataFrame([(i, f"a{i % 20} b{i % 40} c{i}") for i in range(400)], "doc_id long, text string")
    counted = lm.count_pieces(lm.read_blocks(docs, 8), 8, 4)
    found = lm.gather_vocabulary(counted, 4)
    assert found.head == math.isqrt(found.v) > 4 and lm.head_size(10**6) == lm.HEAD


def small(seed=0):
    return Gru(7, 3, 3, 4, np.arange(1, 11).astype(float), seed)


def test_probabilities_sum_to_one():
    g = small()
    h = np.random.default_rng(1).normal(size=(1, 4)).astype(np.float32)
    p = np.exp([g.log_probs(h, np.array([i]))[0][0] for i in range(10)])
    assert p.sum() == pytest.approx(1, abs=1e-5)


def test_gradients_are_those_of_the_loss():
    g = small()
    rng = np.random.default_rng(2)
    inputs, targets, mask = rng.integers(0, 10, (5, 3)), rng.integers(0, 10, (5, 3)), rng.random((5, 3)) < 0.9
    fresh = rng.random((5, 3)) < 0.3
    fresh[0] = True
    h = np.zeros((3, 4), np.float32)
    g.p = {k: v.astype(np.float64) for k, v in g.p.items()}
    loss, grads, _ = g.gradients(inputs, targets, mask, fresh, h)
    for k, v in g.p.items():
        for at in rng.integers(0, v.size, 6):
            old, eps = v.flat[at], 1e-3
            v.flat[at] = old + eps
            up = g.gradients(inputs, targets, mask, fresh, h)[0]
            v.flat[at] = old - eps
            down = g.gradients(inputs, targets, mask, fresh, h)[0]
            v.flat[at] = old
            assert grads[k].flat[at] == pytest.approx((up - down) / (2 * eps), abs=2e-3), k


def test_windows_and_lanes_do_not_change_scores():
    g = small()
    rng = np.random.default_rng(3)
    ids, offsets = rng.integers(0, 10, 200).astype(np.int32), np.array([0, 1, 90, 90, 130, 200])
    a = g.score(ids, offsets, lanes=1, window=200)
    assert np.allclose(a, g.score(ids, offsets, lanes=3, window=7), atol=1e-4)


def test_lanes_cover_every_token_once():
    from bandspark.llm.gru import Lanes

    offsets = np.array([0, 3, 3, 40, 41, 100])
    for lanes, segment in ((1, None), (4, None), (4, 8), (50, 5)):
        dealt, seen = Lanes(offsets, lanes, segment), []
        fresh = []
        for at, mask, begins in dealt.windows(6):
            seen += at[mask].tolist()
            fresh += at[begins].tolist()
        assert sorted(seen) == list(range(100))
        assert set(fresh) == {0, 3, 40, 41} if segment is None else {0, 3, 40, 41} < set(fresh)


def test_a_very_long_text_takes_little_memory():
    import subprocess
    import sys

    code = """
import numpy as np, resource
from bandspark.llm.gru import Gru
g = Gru(1024, 24, 32, 24, np.arange(1, 1049).astype(float))
n = 1_000_000
ids, offsets = np.random.default_rng(1).integers(0, 1048, n + 3000).astype(np.int32), np.concatenate([[0], n + np.arange(0, 3001, 10)])
before = resource.getrusage(resource.RUSAGE_SELF).ru_maxrss
out = g.score(ids, offsets, window=256)
assert np.isfinite(out).all() and len(out) == 301
print((resource.getrusage(resource.RUSAGE_SELF).ru_maxrss - before) // 1024)
"""
    done = subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, check=True, cwd=pathlib.Path(__file__).resolve().parents[2])
    assert int(done.stdout) < 200


def test_logarithms_are_taken_once_for_all_classes(monkeypatch):
    g = Gru(40, 3, 4, 5, np.arange(1, 44).astype(float), 3)
    rng = np.random.default_rng(2)
    states, targets = rng.normal(size=(200, 5)).astype(np.float32), rng.integers(0, 43, 200)
    real, calls = np.log, []
    monkeypatch.setattr(np, "log", lambda *a, **k: calls.append(1) or real(*a, **k))
    got, _ = g.log_probs(states, targets)
    assert len(calls) == 2
    p = {k: v.astype(np.float64) for k, v in g.p.items()}
    soft = lambda x: x - real(np.exp(x).sum())
    want = [soft(h @ p["wc"] + p["bc"])[t // 4] + soft(h @ p["ww"][t // 4] + p["bw"][t // 4])[t % 4] if t < 40 else soft(h @ p["wc"] + p["bc"])[10 + t - 40] for h, t in zip(states.astype(np.float64), targets.tolist(), strict=True)]
    assert np.allclose(got, want, atol=1e-4)


def test_logits_in_bounds_are_not_clipped_and_others_are(monkeypatch):
    """The bound is only looked for where a logit can leave it; pieces of rows give what all rows at once give."""
    from bandspark.llm import gru

    g = Gru(40, 3, 4, 5, np.arange(1, 44).astype(float), 3)
    rng = np.random.default_rng(2)
    states, targets = rng.uniform(-1, 1, (200, 5)).astype(np.float32), rng.integers(0, 43, 200)
    real, calls = gru.clip, []
    monkeypatch.setattr(gru, "clip", lambda *a, **k: calls.append(1) or real(*a, **k))
    grads, pieces = {}, {}
    got, back = g.log_probs(states, targets, grads)
    assert not calls
    monkeypatch.setattr(gru, "ROWS", 7)
    again, back_again = g.log_probs(states, targets, pieces)
    assert np.allclose(got, again, atol=1e-5) and np.allclose(back, back_again, atol=1e-5)
    assert all(np.allclose(grads[k], pieces[k], atol=1e-4) for k in grads)
    g.p["wc"] *= 2000
    far, _ = g.log_probs(states, targets)
    assert calls and np.isfinite(far).all()
