"""Personal data: patterns propose spans, checksums confirm them, words nearby adjust their scores.

Built-in SQL functions only. Base kinds (always reported): email, ip (parts up to 255), card (13 to 19 digits,
Luhn), phone (international, 9 to 15 digits). Added kinds, reported from ``MIN_SCORE``: iban (mod 97), and two weak
shapes that need a telling word nearby, national (a phone number without country code) and taxid (3-2-4 digits).
A span's score is its kind's prior, raised by a checksum that holds and by a context word within
``spans.CONTEXT`` code points on either side, lowered by a word that speaks against it.

The patterns below give the same leftmost non-overlapping matches as the plain ones of the contract, but cannot go back over a
long run: an email's local part starts where its run starts (or where the last match ended), digit runs likewise.

Nulls and edges: null text is empty and has no spans; ids may be null or repeated; other columns are ignored; places are code
points; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bandspark.llm.spans import add_spans, joined

#: The patterns of the base kinds and of the added kinds.
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"(?<![0-9])(?<![0-9][\x20-])[0-9](?:[\x20-]?[0-9]){12,18}+(?![\x20-]?[0-9])",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
    "iban": r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?:\x20?[A-Z0-9]{4}){2,7}(?:\x20?[A-Z0-9]{1,3})?(?![A-Za-z0-9])",
    "national": r"(?<![0-9+)(-])(?<![0-9][\x20.])(?:\([0-9]{3}\)\x20?|[0-9]{3}[\x20.-])[0-9]{3}[\x20.-][0-9]{4}(?![0-9-])",
    "taxid": r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])",
}
BASE = ("email", "ip", "card", "phone")
PRIOR = {"email": 0.8, "ip": 0.5, "card": 0.4, "phone": 0.6, "iban": 0.4, "national": 0.35, "taxid": 0.3}
CHECKSUM_BONUS = 0.4
CONTEXT_BONUS = 0.3
CONTEXT_MALUS = 0.2
MIN_SCORE = 0.6
#: Words that speak for a kind, and words that speak against any.
FOR = {
    "email": "e-?mail|contact|write to|schreib|correo|courriel|@",
    "ip": r"\bip\b|address|host|server|adresse",
    "card": "card|visa|master|amex|credit|karte|tarjeta|carte|payment",
    "phone": "phone|tel\\b|tel\\.|call|fax|mobil|rufnummer|número",
    "iban": "iban|bank|account|konto|compte|cuenta",
    "national": "phone|tel\\b|tel\\.|call|fax|mobil",
    "taxid": "ssn|social security|tax id|taxpayer",
}
AGAINST = r"version|serial|isbn|order no|invoice no|example only"
_BYTE = "0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9])"


def luhn(digits: Column) -> Column:
    return F.call_function("luhn_check", digits)


def mod97(value: Column) -> Column:
    """True if an account number without spaces has the check digits of its kind: letters count from 10, remainder 1."""
    turned = F.concat(F.substr(value, F.lit(5)), F.left(value, F.lit(4)))
    codes = F.transform(F.split(turned, ""), lambda c: F.when(c.rlike("^[0-9]$"), F.ascii(c) - 48).otherwise(F.ascii(c) - 55))
    return F.aggregate(codes, F.lit(0), lambda acc, c: ((acc * F.when(c < 10, F.lit(10)).otherwise(F.lit(100)) + c) % 97).cast("int")) == 1


def _digits(value: Column) -> Column:
    return F.regexp_replace(value, "[^0-9]", "")


def _valid(kind: str, value: Column) -> Column:
    """The condition without which a proposed span is dropped."""
    if kind == "ip":
        return value.rlike(f"^{_BYTE}(?:\\.{_BYTE}){{3}}$")
    if kind == "card":
        return luhn(_digits(value))
    if kind == "phone":
        return F.length(_digits(value)).between(9, 15)
    if kind == "iban":
        return mod97(F.replace(value, F.lit(" "), F.lit("")))
    return F.lit(True)


def _score(kind: str, s: Column) -> Column:
    near = F.lower(F.concat(s["before"], F.lit(" "), s["after"]))
    score = F.lit(PRIOR[kind] + CHECKSUM_BONUS * (kind in ("card", "iban")))
    score = score + F.when(near.rlike(FOR[kind]), F.lit(CONTEXT_BONUS)).otherwise(F.lit(0.0)) - F.when(near.rlike(AGAINST), F.lit(CONTEXT_MALUS)).otherwise(F.lit(0.0))
    return F.round(F.greatest(F.lit(0.0), F.least(F.lit(1.0), score)), 3)


def _confirmed(kind: str, min_score: float) -> Column:
    kept = F.filter(F.col(f"_{kind}"), lambda s: _valid(kind, s["value"]))
    scored = F.transform(kept, lambda s: F.struct(F.lit(kind).alias("kind"), s["start"].alias("start"), s["end"].alias("end"), s["value"].alias("value"), _score(kind, s).alias("score")))
    return scored if kind in BASE else F.filter(scored, lambda s: s["score"] >= min_score)


def of_kind(found: Column, kind: str) -> Column:
    return F.filter(found, lambda s: s["kind"] == kind)


def find_personal_data(docs: DataFrame, min_score: float = MIN_SCORE) -> DataFrame:
    """doc_id and ``found``: an array of kind, start, end, value, score, by kind as listed, then start."""
    text = F.coalesce("text", F.lit(""))
    rows = docs.select("doc_id", text.alias("_text"))
    guards = {"email": F.contains("_text", F.lit("@")), "phone": F.contains("_text", F.lit("+"))}
    rows = add_spans(rows, "_text", {k: (p, guards.get(k, F.lit(True))) for k, p in PATTERNS.items()})
    per = [_confirmed(kind, min_score) for kind in PATTERNS]
    return rows.select("doc_id", F.concat(*per).alias("found"))


def redact(docs: DataFrame, mask: str = "[{kind}]", min_score: float = MIN_SCORE) -> DataFrame:
    """The rows with all their columns, each span found replaced in ``text`` (of overlapping spans the first, then the longest); null texts stay null.

    The text is built from the spans that ``find_personal_data`` reports, so both agree on what is personal data."""
    whole = F.struct(*[F.col(f"`{c}`") for c in docs.columns])
    rows = docs.select(whole.alias("doc_id"), "text")  # the finder carries one column
    found = find_personal_data(rows, min_score).select(F.col("doc_id").alias("doc"), "found")
    ordered = F.array_sort(F.transform("found", lambda s: F.struct(s["start"].alias("start"), (-s["end"]).alias("rev"), s["kind"].alias("kind"))))
    text = F.col("doc.text")
    label = lambda kind: F.concat(F.lit(mask.split("{kind}")[0]), kind, F.lit(mask.split("{kind}")[1])) if "{kind}" in mask else F.lit(mask)
    between = lambda a, b: text.substr((a + 1).cast("int"), (b - a).cast("int"))
    start = F.struct(F.lit("").alias("out"), F.lit(0).cast("long").alias("at"))
    step = lambda acc, s: F.when(s["start"] < acc["at"], acc).otherwise(F.struct(F.concat(acc["out"], between(acc["at"], s["start"]), label(s["kind"])).alias("out"), (-s["rev"]).alias("at")))
    built = F.aggregate(ordered, start, step, lambda acc: F.concat(acc["out"], between(acc["at"], F.length(text).cast("long"))))
    return found.select(*[F.when(text.isNull(), text).otherwise(built).alias(c) if c == "text" else F.col(f"doc.`{c}`").alias(c) for c in docs.columns])


def query(spark, sf_dir: str) -> DataFrame:
    found = find_personal_data(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    counts = [F.size(of_kind(F.col("found"), k)).cast("long").alias(f"n_{k}") for k in PATTERNS]
    base = F.filter("found", lambda s: s["kind"].isin(*BASE))
    return found.select("doc_id", *counts, F.sha2(joined(base), 256).alias("base_sha256"), joined(F.col("found")).alias("spans"), F.transform("found", lambda s: s["score"]).alias("scores"))
