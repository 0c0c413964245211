"""BPE encoding and decoding with a public vocabulary, exact for texts of any length.

White space always ends a token here, so a text is cut at ASCII white space and every different chunk is encoded once
(a bounded memo per task). A chunk longer than ``LONG`` bytes is an unsplit text: its pre-tokens are
encoded by tree concatenation. Leaves of a fixed length are encoded in parallel, neighbours are joined level
by level, and around each join a window of tokens is encoded anew, twice as wide each time, until its first token is the
left side's token there and its last token the right side's (or a side is used up). BPE sequences are right
when all their adjacent pairs are, so what lies outside the window is then right as it stands.

Nulls and edges: null text is empty and has no tokens; ids may be null or repeated; other columns are ignored; an
empty table gives no rows. The vocabulary file is a parameter.
"""

from __future__ import annotations

import hashlib
import json
import re
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from bandspark.llm.textkit import blocks, give_back, small_batches, string_buffer

#: Bytes of a chunk from which it counts as long, characters of a leaf, chunks kept in a task's memo, bytes read at once of a document.
LONG = 1024
LEAF = 512
MEMO = 150_000
PIECE = 1 << 20
#: A word of Latin letters that are single code points in any normal form, and a short tail of marks: two pre-tokens, neither special.
_WORD = re.compile("([A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff]+)([.,;:!?|*#%&$]{0,8})")
_plain = {*range(33, 127), *range(161, 173), *range(174, 256)}  # bytes that byte-level vocabularies write as themselves; the others count from 256
_BYTE_CHARS = {b: 256 + i for i, b in enumerate(b for b in range(256) if b not in _plain)}
_codecs: dict[str, "Codec"] = {}


def codec(path: str) -> "Codec":
    """The codec of a file, one in each worker process, until it is dropped."""
    if path not in _codecs:
        _codecs[path] = Codec(path)
    return _codecs[path]


def drop_codecs() -> None:
    """A task's end: its worker may serve other operators next, which have no use for vocabularies and memos."""
    _codecs.clear()
    give_back()


_GAP = re.compile(rb"[\x20\x09-\x0D]")


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class Codec:
    """Encoder and decoder of one vocabulary file."""

    def __init__(self, path: str, leaf: int = LEAF, long: int = LONG):
        from tokenizers import Tokenizer

        spec = json.load(open(path, encoding="utf-8"))
        self.whole = Tokenizer.from_file(path)
        self.leaf, self.long = leaf, long
        special = [t["content"] for t in spec["added_tokens"]]
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.cut = re.compile("(" + "|".join(map(re.escape, sorted(special, key=len, reverse=True))) + ")") if special else None
        bare = spec | {"added_tokens": [], "normalizer": None, "pre_tokenizer": None, "post_processor": None, "decoder": None}
        self.last = Tokenizer.from_str(json.dumps(bare))  # a pre-token's end
        self.inner = Tokenizer.from_str(json.dumps(bare | {"model": bare["model"] | {"end_of_word_suffix": None}}))  # what is not its end
        self.tokens = {i: t.encode() for t, i in self.whole.get_vocab(with_added_tokens=True).items()}
        suffix = spec["model"]["end_of_word_suffix"] or ""
        self.width = {i: len(t) - len(suffix) * (bool(suffix) and t.endswith(suffix)) for t, i in self.last.get_vocab().items()}  # in mapped characters
        self.memo: dict[bytes, bytes] = {}
        self.stems: dict[str, bytes] = {}
        self.tails: dict[str, bytes] = {}

    # -- unsplit text ----------------------------------------------------------------------------------

    def _encode(self, strings: list[tuple[str, bool]]) -> list[list[int]]:
        """Ids of mapped strings; the flag says whether it ends its pre-token. Both batches run on all threads."""
        out: list[list[int]] = [[]] * len(strings)
        for flag, coder in ((True, self.last), (False, self.inner)):
            at = [i for i, s in enumerate(strings) if s[1] == flag]
            for i, e in zip(at, coder.encode_batch([strings[i][0] for i in at], add_special_tokens=False), strict=True):
                out[i] = e.ids
        return out

    def _join(self, text: str, left: list[int], right: list[int], start: int, mid: int, end: int, final: bool) -> list[int]:
        """Ids of text[start:end] from those of text[start:mid] and text[mid:end]."""
        k = 2
        while True:
            a, b = min(k, len(left)), min(k, len(right))
            lo = mid - sum(self.width[i] for i in left[len(left) - a :])
            hi = mid + sum(self.width[i] for i in right[:b])
            at_start, at_end = a == len(left), b == len(right)
            (window,) = self._encode([(text[lo:hi], final and at_end)])
            agree_left = at_start or window[0] == left[len(left) - a]
            agree_right = at_end or window[-1] == right[b - 1]
            if agree_left and agree_right and (len(window) > 1 or (at_start and at_end)):
                return left[: len(left) - a] + window + right[b:]
            k *= 2

    def encode_unsplit(self, text: str) -> list[int]:
        """Ids of one pre-token of mapped characters."""
        bounds = [*range(0, max(1, len(text)), self.leaf), len(text)]
        parts = self._encode([(text[a:b], b == len(text)) for a, b in zip(bounds, bounds[1:])])
        spans = [(a, b) for a, b in zip(bounds, bounds[1:])]
        while len(parts) > 1:
            new, new_spans = [], []
            for i in range(0, len(parts) - 1, 2):
                (a, m), (_, b) = spans[i], spans[i + 1]
                new.append(self._join(text, parts[i], parts[i + 1], a, m, b, b == len(text)))
                new_spans.append((a, b))
            if len(parts) % 2:
                new.append(parts[-1])
                new_spans.append(spans[-1])
            parts, spans = new, new_spans
        return parts[0]

    def encode_long(self, chunk: str) -> list[int]:
        """Ids of a long chunk without ASCII white space: special tokens first, then pre-tokens."""
        out: list[int] = []
        for part in self.cut.split(chunk) if self.cut else [chunk]:
            if part in self.special:
                out.append(self.special[part])
            elif part:
                for piece, _ in self.whole.pre_tokenizer.pre_tokenize_str(self.whole.normalizer.normalize_str(part)):
                    out += self.encode_unsplit(piece)
        return out

    # -- texts -----------------------------------------------------------------------------------------

    def _word(self, stem: str) -> bytes:
        """Ids of one pre-token of Latin letters: the model alone, without normaliser and pre-tokenizer."""
        low = stem.lower()
        ids = self.stems.get(low)
        if ids is None:
            mapped = low if low.isascii() else low.encode().decode("latin-1").translate(_BYTE_CHARS)
            ids = self.stems[low] = array("I", [t.id for t in self.last.model.tokenize(mapped)]).tobytes()
        return ids

    def learn(self, chunks: set[bytes]) -> None:
        """Puts the ids of new chunks into the memo."""
        if len(self.memo) + len(chunks) > MEMO:
            self.memo.clear()
        if len(self.stems) + len(chunks) > MEMO:
            self.stems.clear()
        other = []
        for c in chunks:
            text = c.decode("utf-8", "replace")
            word = _WORD.fullmatch(text) if len(c) <= self.long else None
            if word:
                ids, tail = self._word(word[1]), word[2]
                if tail:
                    if tail not in self.tails:
                        self.tails[tail] = array("I", self.whole.encode(tail, add_special_tokens=False).ids).tobytes()
                    ids += self.tails[tail]
                self.memo[c] = ids
            elif len(c) <= self.long:
                other.append((c, text))
            else:
                self.memo[c] = array("I", self.encode_long(text)).tobytes()
        for (c, _), e in zip(other, self.whole.encode_batch([t for _, t in other], add_special_tokens=False), strict=True):
            self.memo[c] = array("I", e.ids).tobytes()

    def encode_texts(self, texts: list[bytes]) -> list[bytes]:
        """Ids of each text as little-endian unsigned 32-bit integers."""
        split = [t.split() for t in texts]
        new = set().union(*split) if split else set()
        missing = new - self.memo.keys()
        if missing:
            if len(self.memo) + len(missing) > MEMO:
                missing = new
            self.learn(missing)
        get = self.memo.__getitem__
        return [b"".join(map(get, words)) for words in split]

    def decode(self, ids: bytes) -> bytes:
        """The decoded text in UTF-8: this vocabulary's decoder puts one space between tokens."""
        return b" ".join(map(self.tokens.__getitem__, np.frombuffer(ids, "<u4").tolist()))


def pieces(text: bytes, size: int = PIECE) -> Iterator[bytes]:
    """Cuts a text at white space into pieces of about ``size`` bytes."""
    at = 0
    while len(text) - at > size:
        gap = _GAP.search(text, at + size)
        if not gap:
            break
        yield text[at : gap.start()]
        at = gap.end()
    yield text[at:] if at else text


def _texts(batch: pa.RecordBatch) -> Iterator[list[bytes]]:
    """Blocks of texts of about PIECE bytes."""
    data, offsets = string_buffer(batch.column("text"))
    for a, b in blocks(offsets, PIECE):
        raw = data[offsets[a] : offsets[b]].tobytes()
        cut = (offsets[a : b + 1] - offsets[a]).tolist()
        yield [raw[x:y] for x, y in zip(cut, cut[1:])]


def _digests(codec: Codec, text: bytes) -> tuple[int, str, str]:
    """Of one long text, piece by piece."""
    n, ids_hash, text_hash = 0, hashlib.sha256(), hashlib.sha256()
    for piece in pieces(text):
        (ids,) = codec.encode_texts([piece])
        ids_hash.update(ids)
        if ids:
            text_hash.update((b" " if n else b"") + codec.decode(ids))
        n += len(ids) // 4
    return n, ids_hash.hexdigest(), text_hash.hexdigest()


def encode_documents(docs: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, ids array<int>."""
    path = path or default_path()

    def run(batches):
        coder = codec(path)
        for batch in batches:
            ids = [i for texts in _texts(batch) for i in coder.encode_texts(texts)]
            flat = np.frombuffer(b"".join(ids), "<u4").astype(np.int32)
            offsets = np.zeros(len(ids) + 1, np.int32)
            np.cumsum([len(i) // 4 for i in ids], out=offsets[1:])
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.ListArray.from_arrays(pa.array(offsets), pa.array(flat))], names=["doc_id", "ids"])

    rows = docs.select("doc_id", "text")
    return rows.mapInArrow(run, f"doc_id {rows.schema['doc_id'].dataType.simpleString()}, ids array<int>")


def decode_documents(encoded: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, text: of doc_id, ids."""
    path = path or default_path()

    def run(batches):
        coder = codec(path)
        for batch in batches:
            texts = [coder.decode(np.array(i or [], "<u4").tobytes()).decode("utf-8", "replace") for i in batch.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(texts, pa.string())], names=["doc_id", "text"])

    rows = encoded.select("doc_id", "ids")
    return rows.mapInArrow(run, f"doc_id {rows.schema['doc_id'].dataType.simpleString()}, text string")


def round_trip(docs: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256: every text encoded, and its ids decoded, in one pass."""
    path = path or default_path()

    def run(batches):
        coder = codec(path)
        for batch in small_batches(batches):
            n, ids_sha, text_sha = [], [], []
            for texts in _texts(batch):
                if len(texts) == 1 and len(texts[0]) > 2 * PIECE:
                    found = [_digests(coder, texts[0])]
                else:
                    found = [(len(i) // 4, hashlib.sha256(i).hexdigest(), hashlib.sha256(coder.decode(i)).hexdigest()) for i in coder.encode_texts(texts)]
                for x in found:
                    n.append(x[0])
                    ids_sha.append(x[1])
                    text_sha.append(x[2])
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(ids_sha, pa.string()), pa.array(text_sha, pa.string())], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])
        del coder
        drop_codecs()

    rows = docs.select("doc_id", "text")
    return rows.mapInArrow(run, f"doc_id {rows.schema['doc_id'].dataType.simpleString()}, n_tokens long, ids_sha256 string, decoded_sha256 string")


def query(spark, sf_dir: str) -> DataFrame:
    return round_trip(spark.read.parquet(f"{sf_dir}/documents.parquet"))
