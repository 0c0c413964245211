import hashlib
import random

import numpy as np
import pytest
from tokenizers import Tokenizer

from bandspark.llm import bpe


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(bpe.default_path())


def ids_of(codec, text):
    return np.frombuffer(codec.encode_texts([text.encode()])[0], "<u4").tolist()


ODD = ["", "Été, ÀÉÎ!! straße; µm ªº ÿŸ x_y don.t n.b. |a| ***", " ", "Hello  World's don't 12", "a<|endoftext|>b <|startoftext|><|endoftext|>", "É é İIİ ΑΣ Σ", "foo\xa0bar z​q\x85\x1c", " ́a ́", "日本語！！abc", "x\x00y", "á̂ 각"]


def test_chunks_equal_the_library(library):
    codec = bpe.Codec(bpe.default_path())
    for text in ODD:
        assert ids_of(codec, text) == library.encode(text, add_special_tokens=False).ids, text


@pytest.mark.parametrize("seed", range(6))
def test_tree_concatenation_is_exact(library, seed):
    codec = bpe.Codec(bpe.default_path(), leaf=7, long=20)
    rng = random.Random(seed)
    for _ in range(60):
        alphabet = rng.choice(["a", "ab", "the", "abcdefghijklmnopqrstuvwxyz", "éü日a", "!?.", "in1g", "'s'tlve"])
        text = "".join(rng.choice(alphabet) for _ in range(rng.randint(21, 300)))
        if rng.random() < 0.2:
            text += "<|endoftext|>" + text[::-1]
        assert ids_of(codec, text) == library.encode(text, add_special_tokens=False).ids, text


def test_long_unsplit_text(library):
    codec = bpe.Codec(bpe.default_path())
    for text in ("a" * 60_001, "theing" * 9_000, "".join(random.Random(1).choice("abcdefgh") for _ in range(50_000))):
        assert ids_of(codec, text) == library.encode(text, add_special_tokens=False).ids


def test_pieces_give_the_same_digests(library, monkeypatch):
    monkeypatch.setattr(bpe, "PIECE", 64)
    codec = bpe.Codec(bpe.default_path())
    text = " ".join(f"word{i} \n x" for i in range(200))
    e = library.encode(text, add_special_tokens=False)
    want = (len(e.ids), hashlib.sha256(np.array(e.ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(library.decode(e.ids, skip_special_tokens=False).encode()).hexdigest())
    assert bpe._digests(codec, text.encode()) == want
    assert b" ".join(bpe.pieces(text.encode(), 64)).split() == text.encode().split()


def test_documents_round_trip(spark, library):
    rows = [(i, t, "x") for i, t in enumerate(ODD)] + [(99, None, None), (None, "null id", "y"), (103, "again", "z"), (103, "again", "z")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, ids string")
    for r in bpe.round_trip(docs).join(docs, "doc_id").collect():
        pass
    got = sorted((r.doc_id is None, r.doc_id or 0, r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in bpe.round_trip(docs).collect())
    want = []
    for i, t, _ in rows:
        e = library.encode(t or "", add_special_tokens=False)
        want.append((i is None, i or 0, len(e.ids), hashlib.sha256(np.array(e.ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(library.decode(e.ids, skip_special_tokens=False).encode()).hexdigest()))
    assert got == sorted(want)
    back = {r.doc_id: r.text for r in bpe.decode_documents(bpe.encode_documents(docs.where("doc_id = 4"))).collect()}
    assert back == {4: library.decode(library.encode(ODD[4], add_special_tokens=False).ids, skip_special_tokens=False)}
    assert bpe.round_trip(docs.where("false")).count() == 0


def test_a_task_leaves_no_codec_behind(spark):
    """A worker that has encoded texts holds no vocabulary afterwards: it may serve other operators next."""
    docs = spark.createDataFrame([(i, f"some words number {i}") for i in range(20)], "doc_id long, text string").coalesce(1)
    assert bpe.round_trip(docs).count() == 20

    def held(batches):
        import pyarrow as pa

        from bandspark.llm import bpe as here

        for _ in batches:
            pass
        yield pa.RecordBatch.from_arrays([pa.array([len(here._codecs)])], names=["n"])

    assert [r.n for r in spark.range(4, numPartitions=4).mapInArrow(held, "n long").collect()] == [0] * 4
