import pathlib

import pytest

from bandspark.llm import langid

SF = "/root/testdata/sf0.01"


def test_held_out_accuracy(spark):
    if not pathlib.Path(SF).exists():
        pytest.skip("no test tables")
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    got = langid.query(spark, SF).join(docs, "doc_id").where("held_out and lang is not null and length(text) > 60")
    right = got.where("lang = lang_pred").count()
    assert right >= 0.95 * got.count() > 0


def test_edges(spark):
    rows = [(i, "the cat and the dog of the house that was here " * 3, "en", 1) for i in range(40)] + [(100 + i, "der hund und die katze in dem haus das war ein " * 3, "de", 1) for i in range(40)]
    rows += [(500, None, None, 1), (501, "12 3.4 !!", "en", 1), (502, "", None, 1), (None, "the house", None, 1), (503, "und der hund " * 40_000, None, 1), (503, "und der hund", None, 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, score int")
    dictionaries = langid.learn_dictionaries(docs)
    assert {k for k, _ in dictionaries} == {"en", "de"}
    got = langid.identify(docs, dictionaries).collect()
    assert len(got) == len(rows)
    by = {}
    for r in got:
        by.setdefault(r.doc_id, []).append(r)
    assert all(by[i][0].lang_pred == "und" and by[i][0].score == 0 for i in (500, 501, 502))
    assert by[None][0].lang_pred == "en" and [r.lang_pred for r in by[503]] == ["de", "de"]
    assert all(0 <= r.score <= 1 for r in got)
    assert langid.identify(docs.where("false"), dictionaries).count() == 0
    nothing = docs.withColumn("lang", docs["lang"].substr(100, 1)).where("false")
    assert langid.learn_dictionaries(nothing) == [] and {r.lang_pred for r in langid.identify(docs, []).collect()} == {"und"}


def test_no_language_is_lost_and_the_sample_is_bounded(spark):
    rows = [(7, f"the cat and the dog of house {i}", "en") for i in range(3000)] + [(7, "der hund und die katze " * 9, "de")] * 30 + [(7, "le chat " * 5000 + "zut", "fr")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    found = dict(langid.learn_dictionaries(docs))
    assert list(found) == ["en", "de", "fr"] and found["de"].count(b"katze") == 9
    assert len(found["en"].split(b"the cat")) - 1 <= langid.SAMPLE_PIECES and b"zut" in found["fr"]  # the last piece is a candidate like all others
    assert langid.learn_dictionaries(docs.repartition(13)) == langid.learn_dictionaries(docs)


def test_against_a_plain_compressor(spark):
    import zstandard as z

    if not pathlib.Path(SF).exists():
        pytest.skip("no test tables")
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    dictionaries = langid.learn_dictionaries(docs)

    def plain(text):
        if not text or not any(c.isalpha() for c in text):
            return "und"
        data = langid.normalise(text)
        level = langid.SHORT_LEVEL if len(data) <= langid.SHORT_BYTES else langid.LEVEL
        sizes = []
        for _, content in dictionaries:
            d = z.ZstdCompressionDict(content.ljust(8), dict_type=z.DICT_TYPE_RAWCONTENT)
            c = z.ZstdCompressor(level=level, dict_data=d, write_content_size=False, write_checksum=False, write_dict_id=False)
            sizes.append(sum(len(c.compress(data[a : a + langid.CHUNK])) for a in range(0, len(data), langid.CHUNK)))
        return dictionaries[sizes.index(min(sizes))][0]

    want = {r.doc_id: plain(r.text) for r in docs.select("doc_id", "text").collect()[::10]}
    got = {r.doc_id: r.lang_pred for r in langid.query(spark, SF).collect()}
    assert all(got[k] == v for k, v in want.items())
