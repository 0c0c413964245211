import pathlib
import random

import duckdb
import pyarrow as pa
import pytest
from tests.llm.test_pipeline import classes, shingles

from bandspark.operators.components import connected_components
from bandspark.llm import exactdup, linededup, mixing, ngramjoin

SF = "/root/testdata/sf0.01"


def against_sql(df, sql):
    con = duckdb.connect()
    con.execute(f"create view documents as select * from '{SF}/documents.parquet'")
    want = con.execute(sql).fetchall()
    names = [c[0] for c in con.description]
    assert sorted(map(str, (tuple(r) for r in df.select(*names).collect()))) == sorted(map(str, want))


@pytest.mark.parametrize("module", [exactdup, linededup, ngramjoin, mixing])
def test_whole_table_against_sql(spark, module):
    if not pathlib.Path(SF).exists():
        pytest.skip("no test tables")
    against_sql(module.query(spark, SF), module.ORACLE_SQL)


ODD = [(None, None), (1, ""), (2, None), (3, "a"), (3, "a"), (4, "a"), (None, "a"), (5, "a b c d e f"), (6, "A B C D E F"), (6, "x y"), (7, "x y"), (8, "é x 日")]


def test_exact_edges(spark):
    docs = spark.createDataFrame([(*r, 1) for r in ODD], "doc_id long, text string, kept int")
    rows = exactdup.duplicate_groups(docs).collect()
    assert len(rows) == len(ODD)
    a = [r for r in rows if r.keep_id == 4]
    assert len(a) == 4 and all(r.group_size == 4 for r in a) and [r.doc_id for r in a if r.kept] == [4]
    assert sorted((r.doc_id is None, r.kept) for r in rows if r.keep_id == 2) == [(False, False), (False, True), (True, False)]
    kept = exactdup.drop_duplicates(docs)
    assert kept.columns == docs.columns and kept.count() == len({t or "" for _, t in ODD})
    assert exactdup.duplicate_groups(docs.where("false")).count() == 0
    twice = spark.createDataFrame([(1, "same"), (1, "same")], "doc_id long, text string")
    assert sorted(r.kept for r in exactdup.duplicate_groups(twice).collect()) == [False, True] and exactdup.drop_duplicates(twice).count() == 1


def test_fingerprints_compose(spark):
    import numpy as np

    rng = np.random.default_rng(1)
    data = rng.integers(0, 256, 300_000).astype(np.uint8)
    for base in exactdup.BASES:
        whole = (0, 0)
        for at in range(0, len(data), 50_001):
            part = data[at : at + 50_001]
            whole = exactdup.combine(whole, (exactdup.fingerprint(part)[exactdup.BASES.index(base)], len(part)), base)
        assert whole[0] == exactdup.fingerprint(data)[exactdup.BASES.index(base)]
    small = data[:40]
    want = sum(int(b) * pow(exactdup.BASES[0], 39 - j, exactdup.PRIME) for j, b in enumerate(small)) % exactdup.PRIME
    assert exactdup.fingerprint(small)[0] == want
    docs = spark.createDataFrame([(1, "x" * 70_000), (2, "x" * 70_000), (3, "é" * 40_000), (4, "y")], "doc_id long, text string")
    a, b = (sorted(exactdup.fingerprints(docs, parallel_above=n).collect()) for n in (1 << 30, 1000))
    assert a == b and exactdup.duplicate_groups(docs, parallel_above=1000).where("not kept").count() == 1


def test_join_edges(spark):
    docs = spark.createDataFrame([(*r, 1) for r in ODD], "doc_id long, text string, n int")
    rows = {(r.doc_id, r.n_shingles): r.component_id for r in ngramjoin.similarity_classes(docs).collect()}
    assert rows[(1, 0)] == 1 and rows[(2, 0)] == 2 and rows[(3, 1)] == 3 and rows[(4, 1)] == 3 and rows[(None, 1)] is None
    assert rows[(5, 3)] == 5 and rows[(6, 3)] == 5 and rows[(6, 1)] == 5 and rows[(7, 1)] == 5 and rows[(8, 1)] == 8
    assert ngramjoin.similarity_classes(docs.where("false")).count() == 0


@pytest.mark.parametrize(("seed", "options"), [(1, {}), (1, {"common": 2, "rounds": 0}), (2, {"most_common": 0}), (2, {"common": 2, "most_common": 5, "rounds": 1, "pivots": 2})])
def test_join_finds_every_link_in_crowded_buckets(spark, seed, options, monkeypatch):
    rng = random.Random(seed)
    word = lambda: f"w{rng.randrange(10**6)}"
    base, passage = [word() for _ in range(120)], [word() for _ in range(60)]
    docs = {}
    for i in range(140):  # near copies of one text, at all distances around the limit
        w = list(base)
        for _ in range(rng.randint(0, 7)):
            w[rng.randrange(len(w))] = word()
        docs[i] = " ".join(w[: rng.randint(100, 120)])
    for i in range(140, 200):  # a common passage in texts of their own
        docs[i] = " ".join([word() for _ in range(rng.randint(2, 14))] + passage)
    df = spark.createDataFrame(list(docs.items()), "doc_id long, text string").repartition(4)
    want = classes(docs, 4, 85)
    monkeypatch.setattr(ngramjoin, "SPLIT", 20)
    got = ngramjoin.similarity_classes(df, **options).collect()
    assert {r.doc_id: r.component_id for r in got} == want
    assert all(r.n_shingles == len(shingles(docs[r.doc_id], 4)) for r in got)


def test_pairs_beyond_the_list_do_not_grow_with_its_runs(spark):
    """Fifty groups that share a shingle off the list make rows of a bucket, not fifty times fifty pairs."""
    groups = spark.createDataFrame([(i, 40, [5, 1000 + i]) for i in range(50)] + [(100, 40, [7]), (101, 40, [7])], "g long, n long, cold array<long>")
    rows = ngramjoin._pairs_of_cold(groups, 4, 85, 8).collect()
    assert sorted((r.g, r.h) for r in rows if r.h is not None) == [(100, 101)]
    assert sorted((r.g, r.token, r.rest) for r in rows if r.h is None) == [(i, 5, 40) for i in range(50)]


def test_join_links_inside_a_large_group_of_listless_shingles(spark):
    words = [f"w{i}" for i in range(200)]
    texts = [" ".join([*words, f"end{i}"]) for i in range(60)]
    prefixes = [s[: len(s) - -(-85 * len(s) // 100) + 1].tobytes() for s in ngramjoin.document_sets(pa.array(texts), 4)]
    same = [t for t, p in zip(texts, prefixes) if p == max(prefixes, key=prefixes.count)][:20]
    assert len(same) == 20  # they differ only after the prefix
    df = spark.createDataFrame(list(enumerate(same)), "doc_id long, text string")
    for options in ({"most_common": 1}, {"most_common": 0, "rounds": 0}):
        assert {r.component_id for r in ngramjoin.similarity_classes(df, **options).collect()} == {0}


def test_join_keeps_ids_of_the_first_and_last_spot(spark):
    ids = [194350146, 292653225, 714, 1239, 2526]  # two whose hash is spot 0, and three of the last 32,767 spots
    docs = spark.createDataFrame([(i, "a b c d e") for i in ids], "doc_id long, text string")
    spots = {r.s for r in docs.selectExpr(f"pmod(xxhash64(doc_id), {ngramjoin.ID_BITS}) AS s").collect()}
    assert min(spots) == 0 and len(spots) == 4 and sorted(spots)[1] > ngramjoin.ID_BITS - 32768
    for some in (ids, ids[:2], ids[2:], [ids[0], ids[-1]]):
        wanted = docs.where(docs.doc_id.isin(some)).selectExpr("doc_id AS v")
        assert set(some) <= {r.v for r in ngramjoin.whole_sets(docs, wanted, 4).collect()}
        assert int(ngramjoin.np.unpackbits(ngramjoin.id_filter(wanted)).sum()) == len(some) - (set(ids[:2]) <= set(some))


def test_components(spark):
    rng = random.Random(5)
    edges = [(rng.randrange(300), rng.randrange(300)) for _ in range(200)] + [(i, i + 1) for i in range(400, 460)] + [(9, 9), (None, 3)]
    got = {r.v: r.comp for r in connected_components(spark.createDataFrame(edges, "src long, dst long")).collect()}
    parent = {}

    def find(i):
        while parent.setdefault(i, i) != i:
            i = parent[i]
        return i

    for a, b in edges:
        if a is not None and a != b:
            x, y = sorted((find(a), find(b)))
            parent[y] = x
    assert got == {i: find(i) for i in parent}
    assert connected_components(spark.createDataFrame([], "src long, dst long")).count() == 0


def test_line_edges(spark):
    long = " ".join(f"w{i}" for i in range(60))
    parts = [" ".join(f"p{j}{i}" for i in range(20)) for j in range(3)]
    rows = [(1, f"one\n{long}\nend"), (2, f"two\n{long}\nshort"), (3, "\n".join(parts)), (4, "x\n" + "\n".join(parts) + "\ny"), (5, parts[0]), (6, f"{long}\n{long}"), (None, long), (7, None), (8, ""), (9, long), (9, long)]
    docs = spark.createDataFrame([(*r, "e") for r in rows], "doc_id long, text string, line string")
    got = sorted((r.doc_id or 0, r.n_lines, r.n_deleted, r.deleted) for r in linededup.line_report(docs).collect())
    assert got == sorted([(1, 3, 0, ""), (2, 3, 1, "1:2"), (3, 3, 0, ""), (4, 5, 3, "1:4"), (5, 1, 0, ""), (6, 2, 2, "0:2"), (0, 1, 1, "0:1"), (7, 1, 0, ""), (8, 1, 0, ""), (9, 1, 1, "0:1"), (9, 1, 1, "0:1")])
    out = linededup.without_repeats(docs)
    assert out.columns == docs.columns and {r.text for r in out.where("doc_id in (2, 4)").collect()} == {"two\nshort", "x\ny"}
    assert linededup.line_report(docs.where("false")).count() == 0


def test_mix_properties(spark):
    rows = [(i, "w " * (1 + i % 7), ["a", "b", None, "c"][i % 4] if i else "d", 1) for i in range(400)] + [(None, None, "a", 1), (5, "x y", "b", 1), (5, "x y", "b", 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, size int")
    got = mixing.mix_sources(docs).select("doc.source", "size", "source_size", "target", "taken", "copies").collect()
    assert len(got) == len(rows) and all(r.taken == r.copies * r.size and r.copies <= 3 for r in got)
    total = sum(r.size for r in got)
    targets = {r.source: (r.target, r.source_size) for r in got}
    assert sum(t for t, _ in targets.values()) == pytest.approx(total) and all(t <= 3 * s + 1e-9 for t, s in targets.values())
    for s, (target, _) in targets.items():
        assert abs(sum(r.taken for r in got if r.source == s) - target) <= 7
    out = mixing.mixed_documents(docs)
    assert out.columns == docs.columns and out.count() == sum(r.copies for r in got)
    assert mixing.mix_sources(docs.where("false")).count() == 0


@pytest.mark.parametrize("edge_rows", [7, 100_000])
def test_mix_meets_its_targets_with_equal_and_null_ids(spark, edge_rows):
    equal = [(None, "a b c d e", "x", 1.0)] * 100 + [(None, "a b c d e", "y", 1.0)] * 40 + [(7, f"w{i} " * (i % 9), "z", 1.0) for i in range(120)] + [(7, "q r", None, 1.0)] * 33 + [(None, None, "x", 1.0)] * 3
    docs = spark.createDataFrame(equal, "doc_id long, text string, source string, size double").repartition(7)
    rows = mixing.mix_sources(docs, edge_rows=edge_rows).select("doc.source", "size", "source_size", "target", "taken").collect()
    assert len(rows) == len(equal)
    for source in ("x", "y", "z", None):
        own = [r for r in rows if r.source == source]
        assert abs(sum(r.taken for r in own) - own[0].target) <= max(r.size for r in own) and all(r.taken <= 3 * r.size for r in own)
    again = mixing.mix_sources(docs, edge_rows=3).select("doc.source", "size", "source_size", "target", "taken").collect()
    assert sorted(map(str, rows)) == sorted(map(str, again))
    assert mixing.mixed_documents(docs, edge_rows=edge_rows).columns == docs.columns


def test_the_join_reads_texts_in_small_batches(spark, monkeypatch):
    sizes = []
    before = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    real = ngramjoin.materialize
    monkeypatch.setattr(ngramjoin, "materialize", lambda df, name, *a: sizes.append((name, int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")))) or real(df, name, *a))
    docs = spark.createDataFrame([(i, f"a b c d e f g h i {i % 3}") for i in range(9)], "doc_id long, text string")
    assert {r.component_id for r in ngramjoin.similarity_classes(docs).collect()} == {0, 1, 2}
    assert all(n <= 1000 for name, n in sizes if name in ("join-prints", "join-sets"))
    assert spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch") == before


def test_prefixes_are_packed_in_pieces_of_bounded_size(spark, monkeypatch):
    """However many prefixes a task gets, it sorts and sends a bounded number of shingles at once, and finds the same pairs."""
    groups = spark.createDataFrame([(i, 40, [i // 2 * 100 + j for j in range(7)]) for i in range(400)], "g long, n long, cold array<long>").coalesce(1)
    monkeypatch.setattr(ngramjoin, "PACK", 70)
    at_once = "spark.sql.execution.arrow.maxRecordsPerBatch"
    spark.conf.set(at_once, "10")
    try:
        rows = ngramjoin._pairs_of_cold(groups, 4, 85, 8).collect()
        packed = [len(r.tokens) // 8 for r in ngramjoin._packed_cold(groups, 4).collect()]
    finally:
        spark.conf.unset(at_once)
    assert sorted((r.g, r.h) for r in rows if r.h is not None) == [(i, i + 1) for i in range(0, 400, 2)]
    assert sum(packed) == 2800 and max(packed) <= 140
    assert all(r.h is not None for r in rows)


def test_hash_pieces_leave_small_tables(monkeypatch):
    """Hashes do not depend on where a text is cut into pieces, and the tables that stay in a worker follow the piece, not the text."""
    import numpy as np

    from bandspark.llm import textkit

    data = np.frombuffer((" ".join(f"Word{i * 7919 % 100_003}" for i in range(120_000))).encode(), np.uint8)
    starts, ends, _ = textkit.word_spans(data, np.array([0, len(data)]))
    for name in ("up", "down"):
        monkeypatch.setitem(textkit._power, name, np.ones(1, np.uint64))
    got = textkit.word_hashes(data, starts, ends)
    assert len(data) > 1 << 20 and len(textkit._power["up"]) <= 1 << 17
    monkeypatch.setattr(textkit, "HASH_BYTES", 1 << 22)
    assert (got == textkit.word_hashes(data, starts, ends)).all()
