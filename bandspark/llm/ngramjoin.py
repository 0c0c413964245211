"""Exact similarity join on word shingles by a grouped prefix join, and the classes its links make.

Two documents link when 100 * |A and B| >= PERCENT * |A or B| for their sets of k-word shingles (64-bit hashes).

1. Document counts of all shingles: every task counts its own, packed counts meet per hash range. The shingles
   in more than COMMON documents, at most MOST_COMMON of them, are the common ones (a list with a fixed bound). The
   global order is: other shingles by hash, then common ones from rare to frequent. Any order gives the same result;
   this one keeps frequent shingles out of the prefixes.
2. A document's prefix is its first n - ceil(PERCENT n / 100) + 1 shingles in that order: linked documents share
   one. Documents with equal sets collapse to one; sets with equal size and prefix collapse to one group.
3. Groups that share a shingle which is not common, and whose sizes allow a link, are candidates; group pairs are expanded
   to members and verified on whole sets, as are the pairs inside a group of at most COMMON sets.
4. Sets that share a common shingle are not paired all with all, nor are those of a larger group: if its prefix has only common shingles, its
   sets meet at the first of them; otherwise the group is a bucket of its own. So is a shingle that more than COMMON groups share though the list
   has no room for it: what is past MOST_COMMON costs more buckets, and no link. In each bucket (shingle or group, size class) with more than one
   class, members of other classes are verified against a few seeded pivots, links are contracted to
   classes, and after ROUNDS such rounds what is left of pairs across classes is verified in full. A pair inside
   one class needs no look: it cannot change the classes. Large buckets are dealt to several tasks by a salt.

Nulls and edges: a document without words or text has the empty set and links with nothing; with 1 to k - 1 words its whole
sequence is its one shingle; rows with a null id are never linked and have a null class; repeated rows
are equal sets, and rows that share an id share a class; other columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bandspark.operators.components import connected_components
from bandspark.llm.textkit import blocks, give_back, key_filter, mix, shingle_hashes, small_batches, string_buffer, word_hashes, word_spans, with_maybe
from bandspark.session import arrow_rows, materialize

K, PERCENT = 4, 85
#: A shingle in more documents than this is common; the bound of their list; rounds of pivots, pivots a round.
COMMON, MOST_COMMON = 8, 1_000_000
ROUNDS, PIVOTS = 3, 3
#: Bits of the filter of ids whose sets are compared.
ID_BITS = 1 << 26
#: Shingles a task counts at once.
FLUSH = 1_000_000
#: Texts, or prefixes, sent to a task's Python at once; shingles of prefixes it packs at once.
TEXTS, PACK = 500, 250_000
#: Tasks that a bucket's rows are dealt to, and rows of it that one task meets with all others in the last round.
SALTS, SPLIT = 16, 1000

_U = np.uint64
_LOW = _U(0xFFFFFFFF)


def document_sets(column: pa.Array, k: int) -> Iterator[np.ndarray]:
    """The sorted distinct shingle hashes of every row."""
    data, offsets = string_buffer(column)
    for a, b in blocks(offsets):
        piece, own = data[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]
        starts, ends, rows = word_spans(piece, own)
        shingles, cut = shingle_hashes(word_hashes(piece, starts, ends), rows, k)
        cut = cut.tolist()
        for x, y in zip(cut, cut[1:]):
            yield np.unique(shingles[x:y])


def _bucket(hashes: np.ndarray, buckets: int) -> np.ndarray:
    return ((hashes >> _U(32)) * _U(buckets) >> _U(32)).astype(np.int64)


def _ranges(keys: np.ndarray) -> Iterator[tuple[int, int, int]]:
    """(key, from, to) of the runs of a sorted array."""
    if len(keys):
        cut = np.concatenate([[0], np.flatnonzero(keys[1:] != keys[:-1]) + 1, [len(keys)]]).tolist()
        for a, b in zip(cut, cut[1:]):
            yield int(keys[a]), a, b


def common_shingles(docs: DataFrame, k: int, buckets: int, common: int = COMMON, most: int = MOST_COMMON) -> tuple[np.ndarray, np.ndarray]:
    """(keys sorted, ranks): the shingles in more than ``common`` documents, rare to frequent. A key is the hash range and 32 more bits."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        size = 0

        def flush() -> pa.RecordBatch:
            values, counts = np.unique(np.concatenate(held), return_counts=True)
            at = _bucket(values, buckets)
            low, small = (values & _LOW).astype(np.uint32), np.minimum(counts, 0xFFFF).astype(np.uint16)
            rows = [(key, low[a:b].tobytes(), small[a:b].tobytes() if counts[a:b].max() > 1 else b"") for key, a, b in _ranges(at)]
            return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.binary()), pa.array([r[2] for r in rows], pa.binary())], names=["bucket", "low", "counts"])

        for batch in small_batches(batches):
            for s in document_sets(batch.column(0), k):
                held.append(s)
                size += len(s)
                if size > FLUSH:
                    yield flush()
                    held.clear()
                    size = 0
        if size:
            yield flush()

    def total(table: pa.Table) -> pa.Table:
        lows = [np.frombuffer(x, np.uint32) for x in table.column("low").to_pylist()]
        counts = [np.frombuffer(c, np.uint16) if c else np.ones(len(x), np.uint16) for c, x in zip(table.column("counts").to_pylist(), lows, strict=True)]
        low, n = np.concatenate(lows), np.concatenate(counts)
        order = np.argsort(low, kind="stable")
        low, n = low[order], n[order].astype(np.int64)
        first = np.concatenate([[0], np.flatnonzero(low[1:] != low[:-1]) + 1])
        sums = np.add.reduceat(n, first)
        hot = sums > common
        key = (table.column("bucket")[0].as_py() << 32) + low[first][hot].astype(np.int64)
        return pa.table({"key": pa.array(key), "n": pa.array(sums[hot])})

    packed = docs.select("text").mapInArrow(count, "bucket int, low binary, counts binary")
    counted = packed.groupBy("bucket").applyInArrow(total, "key long, n long")
    found = counted.orderBy(F.desc("n"), "key").limit(most).toArrow()  # at most MOST_COMMON rows of 16 bytes
    key, n = found.column("key").to_numpy(), found.column("n").to_numpy()
    rank = np.empty(len(key), np.int64)
    rank[np.lexsort((key, n))] = np.arange(len(key))
    order = np.argsort(key)
    return key[order], rank[order]


def set_prints(docs: DataFrame, k: int, percent: int, buckets: int, keys: np.ndarray, ranks: np.ndarray) -> DataFrame:
    """doc_id, n, sig_a, sig_b (of the set), pkey (of size and prefix), cold and hot (the prefix, without and with common shingles)."""
    shared = docs.sparkSession.sparkContext.broadcast((keys, ranks))  # bounded by MOST_COMMON

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, ranks = shared.value
        seen = np.zeros(1 << 24, bool)  # a quick no
        seen[keys & 0xFFFFFF] = True
        salt_a, salt_b = _U(0x8CB92BA72F3D8DD7), _U(0x2127599BF4325C37)
        for batch in small_batches(batches):
            numbers, colds, hots = [], [], []
            for s in document_sets(batch.column("text"), k):
                n = len(s)
                p = n - -(-percent * n // 100) + 1 if n else 0
                maybe = np.flatnonzero(seen[(s & _U(0xFFFFFF)).astype(np.int64)]) if len(keys) else np.zeros(0, np.int64)
                if len(maybe):
                    own = (_bucket(s[maybe], buckets) << 32) + (s[maybe] & _LOW).astype(np.int64)
                    at = np.minimum(np.searchsorted(keys, own), len(keys) - 1)
                    yes = keys[at] == own
                    maybe, at = maybe[yes], at[yes]
                cold = np.delete(s, maybe)[:p] if len(maybe) else s[:p]
                hot = s[maybe[np.argsort(ranks[at], kind="stable")]][: p - len(cold)] if len(maybe) and len(cold) < p else s[:0]
                a = int(mix(s ^ salt_a).sum()) if n else 0
                b = int(mix(s * _U(3) + salt_b).sum()) if n else 0
                q = int(mix(np.concatenate([cold, hot]) ^ salt_b).sum()) if n else 0
                numbers.append((n, a, b, q))
                colds.append(cold)
                hots.append(hot)
            cols = np.array(numbers, np.uint64).reshape(-1, 4)
            lists = []
            for x in (colds, hots):
                cut = np.zeros(len(x) + 1, np.int32)
                np.cumsum([len(i) for i in x], out=cut[1:])
                lists.append(pa.ListArray.from_arrays(pa.array(cut), pa.array(np.concatenate([*x, np.zeros(0, _U)]).view(np.int64))))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *[pa.array(cols[:, i].view(np.int64)) for i in range(4)], *lists], names=["doc_id", "n", "sig_a", "sig_b", "pkey", "cold", "hot"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return rows.mapInArrow(run, "doc_id long, n long, sig_a long, sig_b long, pkey long, cold array<long>, hot array<long>")


def _packed_cold(groups: DataFrame, buckets: int) -> DataFrame:
    """The prefixes' shingles that are not common, with group, size and rest, packed by hash range in pieces of about PACK shingles."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, ...]] = []
        size = 0

        def flush() -> pa.RecordBatch:
            tokens, g, n, left = (np.concatenate(x) for x in zip(*held, strict=True))
            order = np.argsort(tokens)
            tokens, g, n, left = tokens[order], g[order], n[order], left[order]
            rows = [(key, tokens[a:b].tobytes(), g[a:b].tobytes(), n[a:b].tobytes(), left[a:b].tobytes()) for key, a, b in _ranges(_bucket(tokens, buckets))]
            return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), *[pa.array([r[i] for r in rows], pa.binary()) for i in (1, 2, 3, 4)]], names=["bucket", "tokens", "gs", "ns", "lefts"])

        for batch in batches:
            lists = batch.column("cold")
            tokens = np.array(lists.flatten().to_numpy(zero_copy_only=False)).view(np.uint64)
            counts = np.diff(lists.offsets.to_numpy())
            g, n = np.repeat(batch.column("g").to_numpy(), counts), np.repeat(batch.column("n").to_numpy().astype(np.int32), counts)
            left = n - (np.arange(len(tokens)) - np.repeat(np.cumsum(counts) - counts, counts)).astype(np.int32)  # shingles from this one on, in the global order
            held.append((tokens, g, n, left))
            size += len(tokens)
            if size > PACK:
                yield flush()
                held.clear()
                size = 0
        if size:
            yield flush()
        give_back()

    return groups.select("g", "n", "cold").where("size(cold) > 0").mapInArrow(pack, "bucket int, tokens binary, gs binary, ns binary, lefts binary")


def _pairs_of_cold(groups: DataFrame, buckets: int, percent: int, common: int) -> DataFrame:
    """(g, h) with g < h: groups that share a shingle which is not common, at places that allow a link; and, of shingles that more than
    ``common`` groups share, rows of token, g and rest (h is null).

    If a pair's first shared shingle is this one, it shares at most what either has from here on; a pair whose first shared
    shingle is another is found, or ruled out, there."""

    def meet(table: pa.Table) -> pa.Table:
        kinds = (("tokens", np.uint64), ("gs", np.int64), ("ns", np.int32), ("lefts", np.int32))
        tokens, g, n, left = (np.concatenate([np.frombuffer(x, kind) for x in table.column(name).to_pylist()]) for name, kind in kinds)
        order = np.argsort(tokens, kind="stable")
        tokens, g, n, left = tokens[order], g[order], n[order].astype(np.int64), left[order].astype(np.int64)
        found = [np.zeros((0, 2), np.int64)]
        step = 1
        _, run, sizes = np.unique(tokens, return_inverse=True, return_counts=True)
        crowded = np.flatnonzero(sizes[run] > common)
        at = np.flatnonzero(sizes[run] <= common)
        while len(at):  # each with the one ``step`` further in its run: at most ``common`` - 1 steps
            at = at[at + step < len(tokens)]
            at = at[tokens[at] == tokens[at + step]]
            x, y = g[at], g[at + step]
            most = np.minimum(left[at], left[at + step])
            ok = (100 * most >= percent * (n[at] + n[at + step] - most)) & (x != y)
            found.append(np.stack([np.minimum(x, y)[ok], np.maximum(x, y)[ok]], axis=1))
            if step % 8 == 0:
                found = [np.unique(np.concatenate(found), axis=0)]
            step += 1
        pairs = np.unique(np.concatenate(found), axis=0)
        none = np.zeros(len(pairs) + len(crowded), bool)
        none[len(pairs) :] = True
        joined = lambda a, b: np.concatenate([a, b])
        cols = joined(pairs[:, 0], g[crowded]), joined(pairs[:, 1], g[crowded]), joined(pairs[:, 0], tokens[crowded].view(np.int64)), joined(pairs[:, 0], left[crowded])
        return pa.table({"g": pa.array(cols[0]), "h": pa.array(cols[1], mask=none), "token": pa.array(cols[2], mask=~none), "rest": pa.array(cols[3], mask=~none)})

    return _packed_cold(groups, buckets).groupBy("bucket").applyInArrow(meet, "g long, h long, token long, rest long")


def id_filter(ids: DataFrame, column: str = "v") -> np.ndarray:
    """A bitmap of ID_BITS bits over hashed ids: at most ID_BITS / 8 bytes whatever the number of ids; it says yes to all of them, and to few others."""
    spot = F.pmod(F.xxhash64(column), F.lit(ID_BITS))
    row, bit = F.shiftright(spot, 15), spot.bitwiseAND(F.lit(32767))  # Spark's own bucket numbers have one bucket more, for spot 0
    parts = ids.groupBy(row.alias("k")).agg(F.bitmap_construct_agg(bit).alias("bits")).collect()
    out = np.zeros((ID_BITS >> 15, 4096), np.uint8)
    for r in parts:
        out[r["k"]] = np.frombuffer(r["bits"], np.uint8)
    return out.ravel()


def whole_sets(docs: DataFrame, wanted: DataFrame, k: int) -> DataFrame:
    """(v, set): sorted arrays of shingle hashes of the documents in ``wanted`` (v), and of a few others."""
    shared = docs.sparkSession.sparkContext.broadcast(id_filter(wanted))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bits = shared.value
        for batch in small_batches(batches):
            spot = batch.column("spot").to_numpy()
            batch = batch.filter(pa.array((bits[spot >> 3] >> (spot & 7).astype(np.uint8) & 1).astype(bool)))
            if not batch.num_rows:
                continue
            sets = list(document_sets(batch.column("text"), k))
            cut = np.zeros(len(sets) + 1, np.int32)
            np.cumsum([len(s) for s in sets], out=cut[1:])
            yield pa.RecordBatch.from_arrays([batch.column("v"), pa.ListArray.from_arrays(pa.array(cut), pa.array(np.concatenate(sets).view(np.int64)))], names=["v", "set"])

    ids = docs.where("doc_id is not null").select(F.col("doc_id").cast("long").alias("v"), "text")
    return ids.withColumn("spot", F.pmod(F.xxhash64("v"), F.lit(ID_BITS))).mapInArrow(run, "v long, set array<long>")


def verify(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) that link, on whole sets."""
    left = pairs.join(sets.withColumnsRenamed({"v": "a", "set": "sa"}), "a")
    both = left.join(sets.withColumnsRenamed({"v": "b", "set": "sb"}), "b")
    common = F.size(F.array_intersect("sa", "sb"))
    return both.select("a", "b", F.size("sa").alias("na"), F.size("sb").alias("nb"), common.alias("i")).where(f"100 * i >= {percent} * (na + nb - i)").select("a", "b").distinct()


def _with_class(rows: DataFrame, classes: DataFrame | None) -> DataFrame:
    if classes is None:
        return rows.withColumn("c", F.col("v"))
    return rows.join(classes.withColumnsRenamed({"v": "_v", "comp": "_c"}), F.col("v") == F.col("_v"), "left").withColumn("c", F.coalesce("_c", "v")).drop("_v", "_c")


def _merge(classes: DataFrame | None, links: DataFrame) -> DataFrame:
    """Classes after more links, contracted to links between classes."""
    if classes is None:
        return materialize(connected_components(links, "a", "b"), "join-classes")
    ends = _with_class(links.withColumnRenamed("a", "v"), classes).select(F.col("c").alias("ca"), F.col("b").alias("v"))
    ends = _with_class(ends, classes).select("ca", F.col("c").alias("cb"))
    new = connected_components(ends, "ca", "cb").withColumnsRenamed({"v": "_o", "comp": "_n"})
    old = classes.join(new, F.col("comp") == F.col("_o"), "left").select("v", F.coalesce("_n", "comp").alias("comp"))
    fresh = new.select(F.col("_o").alias("v"), F.col("_n").alias("comp")).join(classes.select("v"), "v", "left_anti")
    return materialize(old.unionByName(fresh), "join-classes")


def _links_by_id(some: DataFrame, leads: DataFrame, sig: list[str]) -> DataFrame:
    """(a, b): rows that share an id, with different sets, are reachable from each other."""
    ids = materialize(some.groupBy("doc_id").count().where("count > 1").select("doc_id"), "join-ids")
    if ids.isEmpty():
        return some.sparkSession.createDataFrame([], "a long, b long")
    led = some.join(ids, "doc_id", "left_semi").select("doc_id", *sig).distinct().join(leads.select(*sig, "v"), sig)
    first = led.groupBy("doc_id").agg(F.min("v").alias("a"))
    return led.join(first, "doc_id").select("a", F.col("v").alias("b")).where("a <> b").distinct()


def similarity_classes(docs: DataFrame, k: int = K, percent: int = PERCENT, common: int = COMMON, most_common: int = MOST_COMMON, rounds: int = ROUNDS, pivots: int = PIVOTS) -> DataFrame:
    """One row per document: doc_id, n_shingles, component_id (smallest id reachable by links)."""
    spark = docs.sparkSession
    buckets = 4 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    with arrow_rows(spark, TEXTS):
        keys, ranks = common_shingles(docs, k, buckets, common, most_common)
        prints = materialize(set_prints(docs, k, percent, buckets, keys, ranks), "join-prints")
    sig = ["sig_a", "sig_b", "n"]
    some = prints.where("n > 0 and doc_id is not null")
    leads = some.groupBy(*sig).agg(F.min("doc_id").alias("v"), F.first("pkey").alias("pkey"), F.first("cold").alias("cold"), F.first("hot").alias("hot"))
    leads = materialize(leads, "join-leads")
    groups = leads.groupBy("n", "pkey").agg(F.min("v").alias("g"), F.first("cold").alias("cold"), F.count("*").alias("m"))
    members = materialize(leads.select("v", "n", "pkey").join(groups.select("n", "pkey", "g", "m", (F.size("cold") > 0).alias("unlisted")), ["n", "pkey"]).select("g", "v", "n", "m", "unlisted"), "join-members")
    size_class = F.floor(F.log(F.col("n").cast("double")) / float(np.log(100 / percent)) + 1e-9).cast("int")
    # sets by common shingle and size class, each in its own class and the next: sizes that allow a link meet
    hot = leads.where("size(hot) > 0").select("v", "n", size_class.alias("s"), F.size("cold").alias("before"), F.posexplode("hot").alias("at", "token"))
    hot = hot.select("v", "n", "s", "token", (F.col("n") - F.col("before") - F.col("at")).alias("rest"))  # shingles from this one on, in the global order
    crowded = hot.groupBy("token").agg(F.count("*").alias("m")).where("m > 1")
    hot = hot.join(crowded, "token", "left_semi").select("v", "n", "rest", "token", F.explode(F.array(F.col("s"), F.col("s") + 1)).alias("s"))
    # large groups whose first shared shingle is not common: nothing else pairs their members
    large = members.where(f"m > {common} and unlisted").select("v", "n", F.col("n").alias("rest"), F.col("g").alias("token"), size_class.alias("s"))
    groups_of = members.select("g", "v")
    with arrow_rows(spark, TEXTS):
        met = materialize(_pairs_of_cold(groups, buckets, percent, common), "join-met")
    beyond = met.where("h is null").join(members.select("g", "v", "n", size_class.alias("s")), "g").select("v", "n", "rest", "token", F.explode(F.array(F.col("s"), F.col("s") + 1)).alias("s"))
    hot = materialize(hot.unionByName(large).unionByName(beyond).withColumn("salt", F.pmod(F.xxhash64("v"), F.lit(SALTS)).cast("int")), "join-hot")
    # candidates by other shingles, and inside small groups
    pairs = met.where("h is not null").select("g", "h").distinct()
    pairs = pairs.join(groups_of.withColumnRenamed("v", "a"), "g").join(groups_of.withColumnsRenamed({"g": "h", "v": "b"}), "h").select("a", "b")
    small = members.where(f"m > 1 and m <= {common}").select("g", "v")
    inside = small.withColumnRenamed("v", "a").join(small.withColumnRenamed("v", "b"), "g").where("a < b").select("a", "b")
    pairs = materialize(pairs.unionByName(inside).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "join-pairs")
    active = pairs.select(F.col("a").alias("v")).unionByName(pairs.select(F.col("b").alias("v"))).unionByName(hot.select("v"))
    with arrow_rows(spark, TEXTS):
        sets = materialize(whole_sets(docs, active, k), "join-sets")
    seen, classes = pairs, None
    links = materialize(verify(pairs, sets, percent).unionByName(_links_by_id(some, leads, sig)), "join-links")
    if not links.isEmpty():
        classes = _merge(None, links)
    for r in range(rounds + 1):
        if hot.isEmpty():
            break
        now = _with_class(hot, classes)
        first = [F.min_by(F.struct("v", "n", "c", "rest"), F.struct(-F.col("rest"), F.xxhash64("v", F.lit(r))))]  # the one with the fewest shingles of its own
        first += [F.min_by(F.struct("v", "n", "c", "rest"), F.xxhash64("v", F.lit(100 * r + j))) for j in range(1, pivots)]
        stat = now.groupBy("token", "s").agg(F.min("c").alias("lo"), F.max("c").alias("hi"), F.floor(F.count("*") / SPLIT).cast("int").alias("parts"), F.array_distinct(F.array(*first)).alias("ps")).where("lo <> hi")
        stat = materialize(stat, "join-pivots").withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        most = "least(rest, rest2)"
        fits = f"c <> d and 100 * {most} >= {percent} * (n + m - {most})"  # what can be shared from here on allows a link
        bucket = ["token", "s", "salt"]
        if r < rounds:
            other = stat.select(*bucket, F.explode("ps").alias("p")).select(*bucket, F.col("p.v").alias("w"), F.col("p.n").alias("m"), F.col("p.c").alias("d"), F.col("p.rest").alias("rest2"))
            met = now.join(other, bucket).where(fits)
        else:  # all that is left across classes; a large bucket's rows are dealt to parts, each of which meets all of them
            left = materialize(now.join(stat.select(*bucket, "parts"), bucket), "join-left")
            other = left.select("token", "s", F.explode(F.sequence(F.lit(0), F.col("parts"))).alias("part"), F.col("v").alias("w"), F.col("n").alias("m"), F.col("c").alias("d"), F.col("rest").alias("rest2"))
            met = left.withColumn("part", F.pmod(F.xxhash64("v", F.lit(1)), F.col("parts") + 1).cast("int")).join(other, ["token", "s", "part"]).where(f"v < w and {fits}")
        met = met.select(F.least("v", "w").alias("a"), F.greatest("v", "w").alias("b")).distinct()
        new = materialize(met.join(seen, ["a", "b"], "left_anti"), "join-pairs")
        if new.isEmpty():
            if r < rounds:
                continue
            break
        seen = seen.unionByName(new)
        links = materialize(verify(new, sets, percent), "join-links")
        if not links.isEmpty():
            classes = _merge(classes, links)
    label = leads.select(*sig, "v")
    label = materialize(_with_class(label, classes).select(*sig, "c"), "join-labels")
    out = some.select("doc_id", *sig).join(label, sig).select("doc_id", F.col("n").alias("n_shingles"), F.col("c").alias("component_id"))
    none = prints.where("n = 0 or doc_id is null").select("doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("component_id"))
    return out.unionByName(none)


def one_of_each(docs: DataFrame, k: int = K, percent: int = PERCENT) -> DataFrame:
    """The documents that stay: of every class the one of the smallest id, and all that link with nothing."""
    cols = docs.columns
    others = similarity_classes(docs, k, percent).where("doc_id <> component_id").select(F.col("doc_id").alias("_id")).distinct()
    gone = materialize(others, "join-gone")
    marked = with_maybe(docs, F.xxhash64(F.col("doc_id").cast("long")), materialize(key_filter(gone, F.xxhash64("_id")), "join-filter"))
    kept = marked.where("_maybe").join(gone, F.col("doc_id") == F.col("_id"), "left_anti")
    return marked.where("not _maybe").select(*cols).unionByName(kept.select(*cols))


def query(spark, sf_dir: str) -> DataFrame:
    return similarity_classes(spark.read.parquet(f"{sf_dir}/documents.parquet"))


ORACLE_SQL = f"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') AS w FROM documents),
s AS (SELECT doc_id, list_distinct(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < {K} THEN [array_to_string(w, ' ')]
        ELSE list_transform(range(1, len(w) - {K} + 2), lambda i: array_to_string(w[i:i + {K - 1}], ' ')) END) AS sh FROM d),
n AS (SELECT doc_id, len(sh)::BIGINT AS n FROM s),
t AS (SELECT doc_id, unnest(sh) AS x FROM s),
o AS (SELECT a.doc_id AS p, b.doc_id AS q, count(*) AS i FROM t a JOIN t b ON a.x = b.x AND a.doc_id < b.doc_id GROUP BY 1, 2),
l AS (SELECT p, q FROM o JOIN n a ON a.doc_id = p JOIN n b ON b.doc_id = q WHERE 100 * i >= {PERCENT} * (a.n + b.n - i)),
e AS (SELECT p AS u, q AS v FROM l UNION SELECT q, p FROM l),
r(u, c) USING KEY (u) AS (SELECT doc_id, doc_id FROM n UNION
      SELECT e.v, min(r.c) FROM r JOIN e ON e.u = r.u JOIN recurring.r AS k ON k.u = e.v WHERE r.c < k.c GROUP BY e.v)
SELECT n.doc_id, n.n AS n_shingles, r.c AS component_id FROM n JOIN r ON r.u = n.doc_id
"""
