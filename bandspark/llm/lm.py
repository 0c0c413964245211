"""Language-model scores of whole documents: exact unigram base, and a gated recurrent model.

1. Documents are read once, in blocks of about BLOCK_TOKENS tokens. A block keeps its documents as indexes into its list of
   distinct words, and sends that list (64-bit hashes, with counts over its training documents) in pieces by hash range.
2. Pieces meet per hash range: counts over all training documents, sent back to the blocks. No vocabulary is
   ever in one place: the driver gets one row of sums a hash range group, and the most frequent words (HEAD, or the root of all types).
3. Frequent words are tokens of their own, in classes of equal size; the others belong to tail classes by powers of two of
   their count, with P(word | class) = count / count of the class; unseen words share a class with words seen once.
4. The recurrent model starts as the unigram model and learns in ROUNDS rounds: in each, one block of ROUNDS trains from the same
   parameters, so that every training document is learnt from once (truncated backpropagation), and the parameters are averaged by their numbers of tokens, in two steps so that no
   task meets them all. What is gathered grows with the corpus.
   Before that each block and the counts of its words meet once, and its tokens are written as ids of the model: rounds and scores read that table, and shuffle nothing but parameters.
5. Every block is scored with the state carried across windows, so a score is that of the whole document.

Tokens: words (A-Z lowered) and one end per text. Training rows: crc32 of the id as text modulo 7 is not 2.

Nulls and edges: a null text is empty (its only token is the end); a null id counts as the empty string for the fold; repeated
rows are rows of their own; without training rows every count is 0 and the score is the base score; other columns are
ignored; an empty table gives no rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bandspark.llm.gru import Gru
from bandspark.llm.textkit import blocks, string_buffer, word_hashes, word_spans
from bandspark.session import materialize

FOLDS, HELD_OUT = 7, 2
BLOCK_TOKENS = 1_000_000
HEAD, PER_CLASS, TAILS, HIDDEN = 1024, 32, 24, 24
ROUNDS = 2
#: The end of a text, as a hash no word has (words' hashes are of at least one byte).
END = np.uint64(0xE0F5A11B00C0FFEE)
#: Stands for a null id inside blocks.
NO_ID = -(1 << 63)


def _distinct(hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return np.unique(hashes, return_inverse=True)


def _index_planes(index: np.ndarray) -> bytes:
    """Indexes as a plane of low 16 bits and one of the rest, which is nearly constant and packs well."""
    return (index & 0xFFFF).astype("<u2").tobytes() + (index >> 16).astype("<u2").tobytes()


def _from_planes(data: bytes) -> np.ndarray:
    both = np.frombuffer(data, "<u2")
    n = len(both) // 2
    return both[:n].astype(np.int64) | both[n:].astype(np.int64) << 16


def _ranges(keys: np.ndarray) -> Iterator[tuple[int, int, int]]:
    if len(keys):
        cut = np.concatenate([[0], np.flatnonzero(keys[1:] != keys[:-1]) + 1, [len(keys)]]).tolist()
        for a, b in zip(cut, cut[1:]):
            yield int(keys[a]), a, b


def _range_of(hashes: np.ndarray, buckets: int) -> np.ndarray:
    return ((hashes >> np.uint64(32)) * np.uint64(buckets) >> np.uint64(32)).astype(np.int64)


#: Rows of the first pass: a block's documents (bucket -1: ids, fold flags, lengths and token indexes) and its words (bucket 0 and up: hashes, counts).
_SCHEMA = "block long, bucket int, a binary, b binary, c binary, d binary"


def read_blocks(docs: DataFrame, buckets: int, block_tokens: int = BLOCK_TOKENS) -> DataFrame:
    """The first pass; rows as said at _SCHEMA."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, number = TaskContext.get().partitionId(), 0
        held: list[tuple] = []
        size = 0

        def flush() -> pa.RecordBatch:
            nonlocal number
            ids, train, lengths, hashes = (np.concatenate(x) for x in zip(*held, strict=True))
            words, index = _distinct(hashes)
            counts = np.bincount(index, weights=np.repeat(train, lengths), minlength=len(words)).astype(np.uint32)
            at = _range_of(words, buckets)
            block = part << 32 | number
            number += 1
            rows = [(-1, ids.tobytes(), train.tobytes(), lengths.astype(np.int32).tobytes(), _index_planes(index))]
            rows += [(key, words[x:y].tobytes(), counts[x:y].tobytes(), None, None) for key, x, y in _ranges(at)]
            kinds = [pa.int32(), pa.binary(), pa.binary(), pa.binary(), pa.binary()]
            return pa.RecordBatch.from_arrays([pa.array([block] * len(rows), pa.int64()), *[pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)]], names=["block", "bucket", "a", "b", "c", "d"])

        for batch in batches:
            data, offsets = string_buffer(batch.column("text"))
            train = batch.column("train").to_numpy(zero_copy_only=False).astype(np.uint8)
            for x, y in blocks(offsets):
                piece, own = data[offsets[x] : offsets[y]], offsets[x : y + 1] - offsets[x]
                starts, ends, cut = word_spans(piece, own)
                words = word_hashes(piece, starts, ends)
                with_end = np.insert(words, cut[1:], END)
                ids = batch.column("doc_id").slice(x, y - x).fill_null(NO_ID).to_numpy(zero_copy_only=False)
                held.append((ids, train[x:y], np.diff(cut) + 1, with_end))
                size += len(with_end)
                if size >= block_tokens:
                    yield flush()
                    held.clear()
                    size = 0
        if held:
            yield flush()

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", (F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))) % FOLDS != HELD_OUT).alias("train"))
    return rows.mapInArrow(run, _SCHEMA)


#: Rows of the second pass: counts of a block's piece (block 0 and up), and of the hash range (block -1: sums per count class, -2: frequent words).
def count_pieces(read: DataFrame, buckets: int, head: int = HEAD) -> DataFrame:
    def run(table: pa.Table) -> pa.Table:
        bucket = table.column("bucket")[0].as_py()
        pieces = [np.frombuffer(x, np.uint64) for x in table.column("a").to_pylist()]
        own = [np.frombuffer(x, np.uint32) for x in table.column("b").to_pylist()]
        words, index = _distinct(np.concatenate(pieces))
        counts = np.bincount(index, weights=np.concatenate(own), minlength=len(words)).astype(np.int64)
        rows, at = [], 0
        for block, p in zip(table.column("block").to_pylist(), pieces, strict=True):
            rows.append((block, bucket, counts[index[at : at + len(p)]].tobytes(), b""))
            at += len(p)
        seen = counts > 0
        cls = _count_class(counts[seen])
        rows.append((-1, bucket, np.bincount(cls, weights=counts[seen], minlength=64).astype(np.int64).tobytes(), np.bincount(cls, minlength=64).astype(np.int64).tobytes()))
        top = np.lexsort((words, -counts))[: 2 * head_size(buckets * int(seen.sum()), head)]  # as many as all ranges give together, and more
        top = top[counts[top] > 0]
        rows.append((-2, bucket, words[top].tobytes(), counts[top].tobytes()))
        return pa.table({"block": pa.array([r[0] for r in rows], pa.int64()), "bucket": pa.array([r[1] for r in rows], pa.int32()), "a": pa.array([r[2] for r in rows], pa.binary()), "b": pa.array([r[3] for r in rows], pa.binary())})

    return read.where("bucket >= 0").select("block", "bucket", "a", "b").groupBy("bucket").applyInArrow(run, "block long, bucket int, a binary, b binary")


def head_size(types: int, head: int = HEAD) -> int:
    """Frequent words of a vocabulary: at least ``head``, then the root of its types."""
    return max(head, math.isqrt(types))


def _count_class(counts: np.ndarray) -> np.ndarray:
    """0 for counts 0 and 1, then by powers of two."""
    return np.where(counts > 1, np.floor(np.log2(np.maximum(counts, 1))).astype(np.int64), 0)


class Vocabulary:
    """The bounded part that every task holds: frequent words, and mass and types of each count class of the others."""

    def __init__(self, words: np.ndarray, counts: np.ndarray, mass: np.ndarray, types: np.ndarray):
        self.n, self.v = int(mass.sum()), int(types.sum())
        cls = _count_class(counts)
        mass = mass - np.bincount(cls, weights=counts, minlength=64).astype(np.int64)
        types = types - np.bincount(cls, minlength=64)
        order = np.argsort(words)
        self.words, self.ids = words[order], np.arange(len(words))[order]
        self.head = len(words)
        #: classes up to the last that has a word
        self.tails = min(TAILS, int(np.flatnonzero(mass).max(initial=0)) + 1)
        self.mass, self.types = (np.concatenate([x[: self.tails - 1], [x[self.tails - 1 :].sum()]]) for x in (mass, types))
        self.counts = np.concatenate([counts, self.mass])

    def ids_of(self, words: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Model ids of distinct words, and log10 of each one's share of its class (0 for a frequent word)."""
        tail = np.minimum(_count_class(counts), self.tails - 1)
        ids = self.head + tail
        rare = tail == 0
        share = np.where(rare, -np.log10(self.types[0] + self.v + 1.0), np.log10(np.maximum(counts, 1) / np.maximum(self.mass[tail], 1)))
        if self.head:
            at = np.minimum(np.searchsorted(self.words, words), self.head - 1)
            known = self.words[at] == words
            ids = np.where(known, self.ids[at], ids)
            share = np.where(known, 0.0, share)
        return ids.astype(np.int32), share

    def base(self, counts: np.ndarray) -> np.ndarray:
        return np.log10((counts + 1.0) / (self.n + (self.v + 1.0)))


def gather_vocabulary(counted: DataFrame, head: int = HEAD) -> Vocabulary:
    """Sums per count class come as one row (their arrays are added by position), frequent words as at most ``head_size``."""

    def totals(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mass, types = np.zeros(64, np.int64), np.zeros(64, np.int64)
        for batch in batches:
            for a, b in zip(batch.column("a").to_pylist(), batch.column("b").to_pylist(), strict=True):
                mass += np.frombuffer(a, np.int64)
                types += np.frombuffer(b, np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(64)), pa.array(mass), pa.array(types)], names=["k", "mass", "types"])

    def unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, counts = np.zeros(0, np.int64), np.zeros(0, np.int64)
        for batch in batches:  # a task's most frequent words are among its ranges' most frequent words
            words = np.concatenate([words, *[np.frombuffer(x, np.int64) for x in batch.column("a").to_pylist()]])
            counts = np.concatenate([counts, *[np.frombuffer(x, np.int64) for x in batch.column("b").to_pylist()]])
            top = np.lexsort((words, -counts))[:size]
            words, counts = words[top], counts[top]
        yield pa.RecordBatch.from_arrays([pa.array(words), pa.array(counts)], names=["word", "n"])

    sums = counted.where("block = -1").select("a", "b").mapInArrow(totals, "k long, mass long, types long").groupBy("k").agg(F.sum("mass").alias("mass"), F.sum("types").alias("types")).orderBy("k").toArrow()
    mass, types = np.zeros(64, np.int64), np.zeros(64, np.int64)
    mass[sums.column("k").to_numpy()], types[sums.column("k").to_numpy()] = sums.column("mass").to_numpy(), sums.column("types").to_numpy()
    size = head_size(int(types.sum()), head)
    top = counted.where("block = -2").select("a", "b").mapInArrow(unpack, "word long, n long").orderBy(F.desc("n"), "word").limit(size).toArrow()
    return Vocabulary(top.column("word").to_numpy().view(np.uint64), top.column("n").to_numpy(), mass, types)


#: A resolved block: ids, training flags, lengths, base scores, known tokens and log10 shares of its documents, and its tokens as ids of the model.
_RESOLVED = "block long, doc binary, train binary, lengths binary, base binary, known binary, part binary, tokens binary"


def resolve_blocks(read: DataFrame, counted: DataFrame, vocabulary: Vocabulary) -> DataFrame:
    def run(payload: pa.Table, pieces: pa.Table) -> pa.Table:
        if not payload.num_rows:
            return pa.table({"block": pa.array([], pa.int64()), **{k: pa.array([], pa.binary()) for k in ("doc", "train", "lengths", "base", "known", "part", "tokens")}})
        row = payload.slice(0, 1).to_pylist()[0]
        order = np.argsort(pieces.column("bucket").to_numpy(), kind="stable").tolist()
        hashes, counts = pieces.column("h").to_pylist(), pieces.column("n").to_pylist()
        words = np.concatenate([np.frombuffer(hashes[i], np.uint64) for i in order if hashes[i] is not None])
        total = np.concatenate([np.frombuffer(counts[i], np.int64) for i in order if counts[i] is not None])
        lengths, index = np.frombuffer(row["c"], np.int32).astype(np.int64), _from_planes(row["d"])
        owner = np.repeat(np.arange(len(lengths)), lengths)
        ids, part = vocabulary.ids_of(words, total)
        per = lambda x: np.bincount(owner, weights=x[index], minlength=len(lengths))
        cells = {"doc": row["a"], "train": row["b"], "lengths": lengths.tobytes(), "base": per(vocabulary.base(total)).tobytes(), "known": per(total > 0).astype(np.int64).tobytes(), "part": per(part).tobytes(), "tokens": _index_planes(ids[index])}
        return pa.table({"block": pa.array([row["block"]], pa.int64()), **{k: pa.array([v], pa.binary()) for k, v in cells.items()}})

    payload = read.where("bucket = -1").select("block", "a", "b", "c", "d")
    none = F.lit(None).cast("binary")
    pieces = read.where("bucket >= 0").select("block", "bucket", F.col("a").alias("h"), none.alias("n"))
    pieces = pieces.unionByName(counted.where("block >= 0").select("block", "bucket", none.alias("h"), F.col("a").alias("n")))
    return payload.groupBy("block").cogroup(pieces.groupBy("block")).applyInArrow(run, _RESOLVED)


def _average(rows: DataFrame, fan: int = 64) -> np.ndarray | None:
    """Mean of the parameter rows (key, w, p) by weight, first in ``fan`` groups, then of those."""

    def mean(table: pa.Table) -> pa.Table:
        w = table.column("w").to_numpy()
        total, weight = None, float(w.sum())
        for p, x in zip(table.column("p").to_pylist(), w, strict=True):
            part = np.frombuffer(p, np.float64) * (x / max(weight, 1.0))
            total = part if total is None else total + part
        return pa.table({"key": pa.array([0], pa.int64()), "w": pa.array([weight]), "p": pa.array([total.tobytes()], pa.binary())})

    schema = "key long, w double, p binary"
    once = rows.withColumn("key", F.pmod("key", F.lit(fan))).groupBy("key").applyInArrow(mean, schema)
    found = once.groupBy("key").applyInArrow(mean, schema).collect()  # one row of parameters
    return np.frombuffer(found[0]["p"], np.float64) if found and found[0]["w"] > 0 else None


def score_documents(docs: DataFrame, block_tokens: int = BLOCK_TOKENS, rounds: int = ROUNDS, head: int = HEAD) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score."""
    spark = docs.sparkSession
    buckets = 2 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    read = materialize(read_blocks(docs, buckets, block_tokens), "lm-read")
    counted = materialize(count_pieces(read, buckets, head), "lm-counts")
    vocabulary = gather_vocabulary(counted, head)
    resolved = materialize(resolve_blocks(read, counted, vocabulary), "lm-blocks")
    model = Gru(vocabulary.head, vocabulary.tails, PER_CLASS, HIDDEN, vocabulary.counts) if vocabulary.n else None
    shape, n_train = (vocabulary.head, vocabulary.tails, PER_CLASS, HIDDEN, vocabulary.counts), vocabulary.n
    fan = max(64, math.isqrt(resolved.count()))
    for r in range(rounds if model else 0):
        flat = model.pack()

        def learn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for row in _rows(batches):
                keep, lengths = np.frombuffer(row["train"], np.uint8).astype(bool), np.frombuffer(row["lengths"], np.int64)
                tokens = _from_planes(row["tokens"])[np.repeat(keep, lengths)].astype(np.int32)
                own = Gru(*shape).unpack(flat)
                own.train(tokens, np.concatenate([[0], np.cumsum(lengths[keep])]), rate=0.03 / (1 + r))
                yield pa.RecordBatch.from_arrays([pa.array([row["block"]], pa.int64()), pa.array([float(len(tokens))]), pa.array([own.pack().astype(np.float64).tobytes()], pa.binary())], names=["key", "w", "p"])

        turn = F.pmod(F.xxhash64("block", F.lit(3)), F.lit(rounds)) == r
        found = _average(resolved.where(turn).mapInArrow(learn, "key long, w double, p binary"), fan)
        if found is not None:
            model.unpack(found.astype(np.float32))
    flat = model.pack() if model else None

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in _rows(batches):
            doc, train, lengths = np.frombuffer(row["doc"], np.int64), np.frombuffer(row["train"], np.uint8), np.frombuffer(row["lengths"], np.int64)
            base, known = np.frombuffer(row["base"], np.float64), np.frombuffer(row["known"], np.int64)
            scores = base
            if flat is not None:
                net = Gru(*shape).unpack(flat)
                scores = net.score(_from_planes(row["tokens"]).astype(np.int32), np.concatenate([[0], np.cumsum(lengths)])) + np.frombuffer(row["part"], np.float64)
            cols = [pa.array(doc, mask=doc == NO_ID), pa.array(train == 0), pa.array(lengths), pa.array(known), pa.array(np.full(len(doc), n_train)), pa.array(base), pa.array(scores)]
            yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"])

    return resolved.mapInArrow(score, _OUT)


def _rows(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
    """Rows one at a time: a block's tokens are large."""
    for batch in batches:
        for i in range(batch.num_rows):
            yield batch.slice(i, 1).to_pylist()[0]


_OUT = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"


def query(spark, sf_dir: str) -> DataFrame:
    return score_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"))
