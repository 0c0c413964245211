"""Language identification by compression.

For every language that the training rows name, a raw-content zstandard dictionary is made from a bounded sample of pieces
of its texts. A text is lowered, its non-letters become spaces, and it is compressed
with each dictionary in chunks (so a long text costs memory for one chunk, and its evidence adds up over all of
it); the language with the smallest total wins. ``score`` is the winner's share when each byte more
halves a language's weight; a narrow margin gives a low score, and ``accepted`` is false below ``MIN_SCORE``.

Training rows: non-null lang and text, and crc32 of the id as text not divisible by 5. Every training text is cut into pieces of
PIECE_CHARS code points, all of them candidates: a hash of id, text and piece number deals them to SAMPLE_PIECES
buckets a language, and of each bucket the piece of least hash is taken. So a language gives at most SAMPLE_PIECES pieces, equal pieces of equal rows
count once, and no language can be lost; the driver gets that many rows a language.

Nulls and edges: a null text, or one without a letter, is ``und`` with score 0; a null id counts as the empty
string for the fold; repeated rows are rows of their own; ties go to the language with more training rows, then by name;
without training rows everything is ``und``; other columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: The bound of the labelled sample: pieces a language, code points a piece.
SAMPLE_PIECES = 256
PIECE_CHARS = 1024
CHUNK = 2048
#: Compression levels: thorough for short texts, where few bytes decide.
SHORT_BYTES, SHORT_LEVEL, LEVEL = 512, 12, 6
MIN_SCORE = 0.75
FOLDS = 5
UNKNOWN = "und"

_LETTER = re.compile(r"[^\W\d_]")
_PLAIN = bytes(c if 97 <= c <= 122 or c >= 128 else 32 for c in range(256))


def normalise(text: str) -> bytes:
    return text.lower().encode("utf-8", "replace").translate(_PLAIN)


def held_out() -> Column:
    return F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))) % FOLDS == 0


def learn_dictionaries(docs: DataFrame, sample: int = SAMPLE_PIECES, seed: int = 17) -> list[tuple[str, bytes]]:
    """(language, dictionary), most frequent language first."""
    train = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & ~held_out())
    own = F.xxhash64(F.col("doc_id").cast("string"), "text", F.lit(seed))
    last = F.floor(F.greatest(F.length("text") - 1, F.lit(0)) / PIECE_CHARS).cast("int")
    pieces = train.select("lang", own.alias("_own"), "text", F.explode(F.sequence(F.lit(0), last)).alias("_no"))
    pieces = pieces.select("lang", F.xxhash64("_own", "_no").alias("_h"), "_no", "text").withColumn("_bucket", F.pmod("_h", F.lit(sample)))
    least = pieces.groupBy("lang", "_bucket").agg(F.min("_h").alias("_h"), F.sum((F.col("_no") == 0).cast("long")).alias("_rows")).collect()  # at most ``sample`` rows a language
    counts: dict[str, int] = {}
    for r in least:
        counts[r["lang"]] = counts.get(r["lang"], 0) + r["_rows"]
    if not counts:
        return []
    chosen = docs.sparkSession.createDataFrame([(r["lang"], r["_h"]) for r in least], "lang string, _h long")
    piece = F.expr(f"substring(text, _no * {PIECE_CHARS} + 1, {PIECE_CHARS})")
    taken = pieces.join(F.broadcast(chosen), ["lang", "_h"]).groupBy("lang", "_h").agg(F.min(piece).alias("_text"))  # bounded as the rows above
    found: dict[str, list] = {k: [] for k in counts}
    for r in taken.collect():
        found[r["lang"]].append((r["_h"], r["_text"]))
    order = sorted(counts, key=lambda k: (-counts[k], k))
    return [(k, b" ".join(normalise(t) for _, t in sorted(found[k]))) for k in order]


class Classifier:
    def __init__(self, dictionaries: list[tuple[str, bytes]]):
        import zstandard as z

        self.names = [k for k, _ in dictionaries]
        self.coders = {}
        for level in (LEVEL, SHORT_LEVEL):
            self.coders[level] = []
            for _, content in dictionaries:
                d = z.ZstdCompressionDict(content.ljust(8), dict_type=z.DICT_TYPE_RAWCONTENT)
                d.precompute_compress(level=level)
                self.coders[level].append(z.ZstdCompressor(level=level, dict_data=d, write_content_size=False, write_checksum=False, write_dict_id=False))

    def sizes(self, text: str) -> list[int]:
        data = normalise(text)
        chunks = [data[a : a + CHUNK] for a in range(0, len(data), CHUNK)]
        return [sum(len(c.compress(x)) for x in chunks) for c in self.coders[SHORT_LEVEL if len(data) <= SHORT_BYTES else LEVEL]]

    def predict(self, text: str | None) -> tuple[str, float]:
        if not text or not self.names or not _LETTER.search(text):
            return UNKNOWN, 0.0
        sizes = self.sizes(text)
        best = min(range(len(sizes)), key=sizes.__getitem__)
        return self.names[best], 1 / sum(2.0 ** -min(60, s - sizes[best]) for s in sizes)


def identify(docs: DataFrame, dictionaries: list[tuple[str, bytes]], min_score: float = MIN_SCORE) -> DataFrame:
    """doc_id, held_out, lang_pred, score, accepted."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = Classifier(dictionaries)
        for batch in batches:
            found = [model.predict(t) for t in batch.column("text").to_pylist()]
            scores = pa.array([s for _, s in found], pa.float64())
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), batch.column("held_out"), pa.array([k for k, _ in found], pa.string()), scores, pa.array([s >= min_score for _, s in found], pa.bool_())],
                names=["doc_id", "held_out", "lang_pred", "score", "accepted"],
            )

    rows = docs.select("doc_id", held_out().alias("held_out"), "text")
    return rows.mapInArrow(run, f"doc_id {rows.schema['doc_id'].dataType.simpleString()}, held_out boolean, lang_pred string, score double, accepted boolean")


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return identify(docs, learn_dictionaries(docs))
