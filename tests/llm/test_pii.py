import hashlib
import pathlib
import re

import pytest

from bandspark.llm import pii

PLAIN = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def luhn(d):
    return sum(int(c) if i % 2 == 0 else sum(divmod(2 * int(c), 10)) for i, c in enumerate(reversed(d))) % 10 == 0


def brute(text):
    out = []
    for kind, p in PLAIN.items():
        for m in re.finditer(p, text):
            d = re.sub("[^0-9]", "", m[0])
            if kind == "ip" and max(map(int, m[0].split("."))) > 255:
                continue
            if kind == "card" and not (13 <= len(d) <= 19 and luhn(d)):
                continue
            if kind == "phone" and not 9 <= len(d) <= 15:
                continue
            out.append((kind, m.start(), m.end()))
    return out


ODD = [
    None, "", "a@b.c_d@e.f", "x@y", "1.2.3.4.5.6.7.8 999.1.1.1.1 0001.02.3.255", "4111 1111 1111 1111 and 4111-1111-1111-1112", "7 - 4111111111111111", "12345678901234567890123 4111111111111111",
    "+1 (017) 555-7713 +12345678- +1)(2", "é😀 mail: ünï.a@b.co 😀 +49 170 1234567", "a@b.c" * 30, "a.b@" + "c." * 5000 + "d", "+" * 50 + "1 2", "1.1.1.1" * 40, "my iban DE89 3704 0044 0532 0130 00 ok", "DE89370400440532013001",
    "call (415) 555-2671 now", "ssn 123-45-6789", "123-45-6789", "A" * 100_000, "1 " * 60_000, "x@y.z " * 1500,
]


def check(rows, texts):
    for r in rows:
        want = brute(texts[r.doc_id] or "")
        joined = ",".join(f"{k}:{a}:{b}" for k, a, b in want)
        assert [r.n_email, r.n_ip, r.n_card, r.n_phone] == [sum(w[0] == k for w in want) for k in PLAIN], (r.doc_id, want, r.spans)
        assert r.base_sha256 == hashlib.sha256(joined.encode()).hexdigest(), (texts[r.doc_id] or "")[:100]
        assert set(joined.split(",")) - {""} <= set(r.spans.split(","))


def run(spark, tmp_path, texts):
    path = str(tmp_path / "documents.parquet")
    spark.createDataFrame([(i, t, 1) for i, t in enumerate(texts)], "doc_id long, text string, found int").write.parquet(path)
    return pii.query(spark, str(tmp_path)).collect()


def test_odd_texts(spark, tmp_path):
    rows = run(spark, tmp_path, ODD)
    assert len(rows) == len(ODD)
    check(rows, ODD)
    by = {r.doc_id: r.spans for r in rows}
    assert "iban:8:35" in by[14] and "iban" not in by[15]
    assert "national:5:19" in by[16] and "taxid:4:15" in by[17] and "taxid" not in by[18]


def test_whole_table_against_brute_force(spark):
    sf = "/root/testdata/sf0.01"
    if not pathlib.Path(sf).exists():
        pytest.skip("no test tables")
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()}
    check(pii.query(spark, sf).collect(), texts)


def test_empty_table_and_repeats(spark):
    docs = spark.createDataFrame([(1, "a@b.co"), (1, "a@b.co"), (None, "1.2.3.4")], "doc_id long, text string")
    assert pii.find_personal_data(docs.where("false")).count() == 0
    assert sorted(len(r.found) for r in pii.find_personal_data(docs).collect()) == [1, 1, 1]
    assert sorted(r.text for r in pii.redact(docs).collect()) == ["[email]", "[email]", "[ip]"]


def test_context_reaches_over_neighbouring_matches(spark):
    from pyspark.sql import functions as F

    from bandspark.llm.spans import CONTEXT, add_spans

    text = "é call 55 / 66, " + "7 " * 30 + "x" * 50 + " 8"
    row = add_spans(spark.createDataFrame([(text,)], "_text string"), "_text", {"n": ("[0-9]+", F.lit(True))}).first()
    want = [(m.start(), m[0], text[max(0, m.start() - CONTEXT) : m.start()], text[m.end() : m.end() + CONTEXT]) for m in re.finditer("[0-9]+", text)]
    assert [(s.start, s.value, s.before, s.after) for s in row["_n"]] == want


def test_redact_masks_what_is_found_and_nothing_else(spark):
    rows = [(1, "host at 10.0.0.1. and 999.1.1.1", "x"), (2, "card 4111 1111 1111 1111, not 4111 1111 1111 1112", "y"), (3, "a.b@c.example.com é +1 (212) 555-0147 or +1 22", None), (4, None, "z"), (5, "", "z"), (None, "nothing here", "z")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, found string")
    got = pii.redact(docs)
    assert got.columns == docs.columns
    out = {r.doc_id: r.text for r in got.collect()}
    assert out == {1: "host at [ip]. and 999.1.1.1", 2: "card [card], not 4111 1111 1111 1112", 3: "[email] é [phone] or +1 22", 4: None, 5: "", None: "nothing here"}
    for r in pii.find_personal_data(got.where("text is not null")).collect():
        assert not [s for s in r.found if s.kind in pii.BASE]
