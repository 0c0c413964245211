"""Places of all matches of a pattern, with built-in SQL functions only.

``regexp_extract_all`` gives the matches and ``split`` by the same pattern the gaps between them; running sums of their
lengths (in code points) are the places. Running sums are made in chunks, so they cost little more than linear time.
Patterns are Java's; those with a long tail use possessive repeats, so that they neither recurse nor go back.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Code points of context kept on each side of a span.
CONTEXT = 40
_CHUNK = 256


def _last(a: Column) -> Column:
    return F.get(a, F.size(a) - 1)


def running_sums(steps: Column) -> Column:
    """Inclusive running sums of a non-empty array of whole numbers."""
    chunks = F.transform(F.sequence(F.lit(0), F.floor((F.size(steps) - 1) / _CHUNK).cast("int")), lambda c: F.slice(steps, c * _CHUNK + 1, F.lit(_CHUNK)))
    none = F.array().cast("array<bigint>")
    inner = F.transform(chunks, lambda ch: F.aggregate(ch, none, lambda acc, x: F.concat(acc, F.array(F.coalesce(_last(acc), F.lit(0).cast("bigint")) + x))))
    return F.flatten(_shifted(inner))


def _shifted(inner: Column) -> Column:
    zero = F.array(F.lit(0).cast("bigint"))
    offsets = F.aggregate(inner, zero, lambda acc, p: F.concat(acc, F.array(_last(acc) + _last(p))))
    both = F.arrays_zip(inner.alias("p"), F.slice(offsets, F.lit(1), F.size(inner)).alias("o"))
    return F.transform(both, lambda b: F.transform(b["p"], lambda x: x + b["o"]))


def add_spans(df: DataFrame, text: str, kinds: dict[str, tuple[str, Column]]) -> DataFrame:
    """Adds for every kind (pattern, guard) a column ``_<kind>``: array of start, end (exclusive), value, before, after.

    The guard is a cheap condition without which the pattern cannot match."""
    nothing = F.array().cast("array<string>")
    df = df.withColumns({f"_m_{k}": F.when(guard, F.regexp_extract_all(F.col(text), F.lit(p), F.lit(0))).otherwise(nothing) for k, (p, guard) in kinds.items()})
    df = df.withColumns({f"_g_{k}": F.when(F.size(f"_m_{k}") > 0, F.split(F.col(text), p, -1)).otherwise(nothing) for k, (p, _) in kinds.items()})
    step = {f"_e_{k}": F.when(F.size(f"_m_{k}") > 0, _ends(F.col(f"_m_{k}"), F.col(f"_g_{k}"))).otherwise(F.array().cast("array<bigint>")) for k in kinds}
    df = df.withColumns(step)
    out = {f"_{k}": _spans(F.col(text), F.col(f"_m_{k}"), F.col(f"_g_{k}"), F.col(f"_e_{k}")) for k in kinds}
    return df.withColumns(out).drop(*[f"_{x}_{k}" for k in kinds for x in "mge"])


def _ends(m: Column, g: Column) -> Column:
    return running_sums(F.transform(m, lambda x, i: (F.length(F.get(g, i)) + F.length(x)).cast("bigint")))


def _near(text: Column, gap: Column, cut: Column, start: Column, n: Column) -> Column:
    """``cut`` of the gap to the next match if that is long enough, else of the whole text: other matches are context as well."""
    return F.when(F.length(gap) >= CONTEXT, cut).otherwise(text.substr((start + 1).cast("int"), n.cast("int")))


def _spans(text: Column, m: Column, g: Column, e: Column) -> Column:
    return F.transform(
        m,
        lambda x, i: F.struct(
            (F.get(e, i) - F.length(x)).alias("start"),
            F.get(e, i).alias("end"),
            x.alias("value"),
            _near(text, F.get(g, i), F.right(F.get(g, i), F.lit(CONTEXT)), F.greatest(F.get(e, i) - F.length(x) - CONTEXT, F.lit(0)), F.least(F.get(e, i) - F.length(x), F.lit(CONTEXT))).alias("before"),
            _near(text, F.get(g, i + 1), F.left(F.get(g, i + 1), F.lit(CONTEXT)), F.get(e, i), F.lit(CONTEXT)).alias("after"),
        ),
    )


def joined(spans: Column) -> Column:
    """kind:start:end, comma-joined, of an array of spans with those fields."""
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
