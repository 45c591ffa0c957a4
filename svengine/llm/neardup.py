"""Near-duplicates: consistent weighted sampling over TF-IDF shingles, banded, verified by weighted Jaccard similarity.

Words are lower-cased and split at ASCII white space; a shingle is WORDS words (all words of a shorter text). Its weight is
(1 + ln tf) * (1 + ALPHA * idf), with idf between 0 and 1 from document frequencies counted over all documents in a table of
CELLS hashed cells, whose size doesn't grow: a cell counts the documents with any of its shingles, so a rare shingle's frequency is at least that of its
cell (with n documents of s shingles about n * s / CELLS), and idf tells frequent shingles from others, not rare ones apart. ALPHA is small on purpose: in a large group of near copies the shared shingles are frequent and the
differing ones rare, and full idf weights would hide such copies.

Each document gets SAMPLES improved consistent weighted samples; documents that agree in all rows of a band share a bucket. Equal texts are
folded first, so buckets hold different texts only. Within a bucket pairs aren't listed. A bucket's centre is the text whose buckets have the most texts, as it
is like the most of the others. Each text is compared with the best centre of its buckets, and each bucket's centre with members that these links don't join to it; then
the pairs of different components that share a bucket are compared, but for those whose weights, summed by groups of shingles, can't reach the similarity; shingles
that only one of these texts has are in no sum. So every other pair in a bucket is either compared or already in one class. Classes are connected components,
found by distributed label propagation. A centre's text is replicated for every SALT members, so no task holds a large group.

The samples' random numbers come from pools of 2**POOL_BITS entries, picked by hashes of shingle and sample; in a text of more shingles than that, shingles share
entries, which leaves each sample's chance of agreeing as it is and correlates samples a little.

Texts without words are one class. Null counts as empty. Rows with the same doc_id are separate rows; if their texts differ, the class of one of them
counts for both. Rows without a doc_id can't be named by pairs and get no row.
"""

from __future__ import annotations

import functools
import hashlib

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

WORDS, SIMILARITY = 5, 0.8
ALPHA = 0.1
CELLS, BLOCKS = 1 << 20, 64
#: Samples, and bands of ROWS of them: SHUFFLES orders of the samples are each cut into bands. A pair of similarity 0.8 has about 34
#: equal samples and shares no band with a probability below 1e-3; one of 0.2 shares one with a probability of 1 %.
SAMPLES, ROWS, SHUFFLES = 42, 5, 5
BANDS = SHUFFLES * (SAMPLES // ROWS)
POOL_BITS = 16
#: Members, and bytes of their texts, that are compared with one copy of a centre on average.
SALT, SALT_BYTES = 64, 16_000_000
#: Shingles times samples that are drawn at once, which bounds a worker's memory for very long texts.
STEP = 1 << 18
#: A table of (long, long, int) rows up to this count is broadcast: 24 MB.
BROADCAST_ROWS = 1_000_000
#: Draws for more samples, which only tests use.
MORE = 384
#: Groups of shingles, LANES to a long, whose weights are summed in units of 1 / UNITS, up to CAP each.
LANES, UNITS, CAP = 7, 32, 127
GROUPS = 37 * LANES
_MIX = np.uint64(0x9E3779B97F4A7C15)


def _mixed(x: np.ndarray) -> np.ndarray:
    """A bijective mix of 64-bit values."""
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(0xD6E8FEB86659FD93)
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


def shingles(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """The distinct shingles' hashes, sorted, and how often each occurs."""
    words = (text or "").lower().encode().split()
    h = np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))
    n = max(1, len(h) - WORDS + 1) if len(h) else 0
    out = np.zeros(n, np.uint64)
    for k in range(min(WORDS, len(h))):
        out = _mixed(out * _MIX + h[k : k + n])
    return np.unique(out, return_counts=True)


def cell(h: np.ndarray) -> np.ndarray:
    return (h >> np.uint64(44)).astype(np.int64)


def cells(h: np.ndarray) -> np.ndarray:
    """The distinct cells of sorted hashes: each counts once a document."""
    c = cell(h)
    return c[np.concatenate([[True], c[1:] != c[:-1]])] if len(c) else c


def document_frequencies(texts: DataFrame) -> tuple[np.ndarray, int]:
    """Documents with a shingle in each cell, over all rows, and the number of rows. The cells' number bounds what the driver gets."""
    width = CELLS // BLOCKS

    def count(batches):
        from pyspark import TaskContext

        sums = np.zeros(CELLS, np.uint32)
        for b in batches:
            got = [cells(shingles(t.as_py())[0]) for t in b.column(0)]
            if got:
                sums += np.bincount(np.concatenate(got), minlength=CELLS).astype(np.uint32)
        salt, z = TaskContext.get().partitionId() % 16, zstandard.ZstdCompressor(level=1)
        blocks = [k for k in range(BLOCKS) if sums[k * width : (k + 1) * width].any()]
        yield pa.RecordBatch.from_arrays([pa.array(blocks, pa.int32()), pa.array([salt] * len(blocks), pa.int32()), pa.array([z.compress(sums[k * width : (k + 1) * width].astype("<u8").tobytes()) for k in blocks], pa.binary())], ["block", "salt", "counts"])

    def add(t):
        d, z = zstandard.ZstdDecompressor(), zstandard.ZstdCompressor(level=1)
        total = sum(np.frombuffer(d.decompress(x), "<u8") for x in t["counts"].to_pylist())
        return pa.table({"block": t["block"][:1], "salt": pa.array([0], pa.int32()), "counts": pa.array([z.compress(total.tobytes())], pa.binary())})

    kind = "block int, salt int, counts binary"
    parts = texts.select("text").mapInArrow(count, kind).groupBy("block", "salt").applyInArrow(add, kind).groupBy("block").applyInArrow(add, kind)
    out, d = np.zeros(CELLS, np.int64), zstandard.ZstdDecompressor()
    for r in parts.collect():
        out[r["block"] * width : (r["block"] + 1) * width] = np.frombuffer(d.decompress(bytes(r["counts"])), "<u8")
    return out, texts.count()


def idf_weights(df: np.ndarray, n: int) -> np.ndarray:
    """1 + ALPHA * idf for each cell; idf is 1 for a cell of one document and 0 for one of all."""
    return (1 + ALPHA * np.clip(np.log((n + 1) / (df + 1)) / np.log(n + 2), 0, 1)).astype(np.float32)


def weighted(text: str | None, idf: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    h, tf = shingles(text)
    return h, ((1 + np.log(tf)) * idf[cell(h)]).astype(np.float32)


def weighted_jaccard(a: tuple, b: tuple) -> float:
    """Sum of the lesser weights over the sum of the greater ones; 1 for two texts without shingles."""
    _, i, j = np.intersect1d(a[0], b[0], assume_unique=True, return_indices=True)
    total = float(a[1].sum(dtype=np.float64) + b[1].sum(dtype=np.float64))
    both = float(np.minimum(a[1][i], b[1][j]).sum(dtype=np.float64))
    return both / (total - both) if total else 1.0


@functools.lru_cache(maxsize=1)
def _draws(seed: int = 11):
    """Pools of the sampling scheme's random numbers (gamma(2,1) twice and uniform), and a multiplier for each sample."""
    rng = np.random.default_rng(seed)
    n = 1 << POOL_BITS
    r = rng.gamma(2.0, 1.0, n).astype(np.float32) + np.float32(1e-6)
    ln_c = np.log(rng.gamma(2.0, 1.0, n)).astype(np.float32)
    beta = rng.random(n).astype(np.float32)
    odd = rng.integers(0, 1 << 63, SAMPLES, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    bands = np.concatenate([rng.permutation(SAMPLES)[: SAMPLES // ROWS * ROWS].reshape(-1, ROWS) for _ in range(SHUFFLES)])
    bits = rng.integers(0, 1 << 63, MORE, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    return r, ln_c, beta, odd, bands, bits


def samples(h: np.ndarray, w: np.ndarray, odd: np.ndarray) -> np.ndarray:
    """For each sample the chosen shingle and its level, mixed into 64 bits: equal with the probability of the weighted Jaccard similarity."""
    r_, c_, b_ = _draws()[:3]
    n = max(1, STEP // len(odd))
    best = np.full(len(odd), np.inf, np.float32)
    out = np.zeros(len(odd), np.uint64)
    for at in range(0, len(h), n):
        hh, ln_w = h[at : at + n], np.log(w[at : at + n])[:, None]
        k = ((hh[:, None] * odd) >> np.uint64(64 - POOL_BITS)).astype(np.int32)
        r, beta = r_[k], b_[k]
        t = np.floor(ln_w / r + beta)
        ln_a = c_[k] - r * (t - beta + 1)
        i = ln_a.argmin(0)
        cols = np.arange(len(odd))
        low = ln_a[i, cols]
        level = t[i, cols].astype(np.int64).astype(np.uint64)
        got = _mixed(hh[i] * _MIX + level)
        better = low < best
        best = np.where(better, low, best)
        out = np.where(better, got, out)
    return out


def band_keys(h: np.ndarray, w: np.ndarray) -> np.ndarray:
    s = samples(h, w, _draws()[3])[_draws()[4]]
    key = np.arange(1, BANDS + 1, dtype=np.uint64) * _MIX
    for k in range(ROWS):
        key = _mixed(key * _MIX + s[:, k])
    return key.view(np.int64)


def sketches(texts: DataFrame, idf) -> DataFrame:
    """doc_id, digest of the text (of nothing, for texts without words), bytes of the text, bucket keys (none for texts without words)."""

    def run(batches):
        table = idf.value
        for b in batches:
            digests, sizes, keys = [], [], []
            for t in b.column(1):
                s = t.as_py() or ""
                h, w = weighted(s, table)
                raw = s.encode()
                digests.append(hashlib.sha256(raw if len(h) else b"").digest())
                sizes.append(len(raw))
                keys.append(band_keys(h, w) if len(h) else np.zeros(0, np.int64))
            at = np.concatenate([[0], np.cumsum([len(k) for k in keys])]).astype(np.int32)
            lists = pa.ListArray.from_arrays(pa.array(at), pa.array(np.concatenate(keys) if keys else np.zeros(0, np.int64)))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(digests, pa.binary()), pa.array(sizes, pa.int64()), lists], ["doc_id", "digest", "size", "keys"])

    return texts.mapInArrow(run, "doc_id long, digest binary, size long, keys array<long>")


def packed_sums(h: np.ndarray, w: np.ndarray, alone: np.ndarray | None = None) -> tuple[np.ndarray, int, float]:
    """The weights' sums by group of shingles, rounded up to units and packed; the units above CAP; the sum of all weights.

    alone: hashes of shingles that no text to compare with has. They are in no common weight, so they count in the sum of all weights only.
    """
    common_w = w.astype(np.float64) if alone is None else np.where(np.isin(h, alone), 0.0, w)
    units = np.ceil(np.bincount((h & np.uint64(0xFFFFFFFF)).astype(np.int64) % GROUPS, common_w, GROUPS) * UNITS).astype(np.int64)
    low = np.minimum(units, CAP)
    return (low.reshape(-1, LANES) << (8 * np.arange(LANES))).sum(1), int((units - low).sum()), float(w.sum(dtype=np.float64))


def unshared(texts: DataFrame) -> DataFrame:
    """id and alone, the hashes of the shingles that are in no other row of texts (doc_id, text)."""

    def run(batches):
        for b in batches:
            got = [shingles(t.as_py())[0] for t in b.column(1)]
            ids = np.repeat(np.asarray(b.column(0).to_pylist(), np.int64), [len(h) for h in got])
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(np.concatenate([np.zeros(0, np.uint64), *got]).view(np.int64))], ["id", "h"])

    hashes = texts.select("doc_id", "text").mapInArrow(run, "id long, h long").groupBy("h").agg(F.min("id").alias("id"), F.count(F.lit(1)).alias("n"))
    return hashes.where("n = 1").groupBy("id").agg(F.collect_list("h").alias("alone"))


def signatures(texts: DataFrame, wanted: DataFrame, idf) -> DataFrame:
    """id and packed_sums, for comparisons with each other, of the texts whose doc_id is an id of wanted."""

    def run(batches):
        table = idf.value
        for b in batches:
            got = [packed_sums(*weighted(t.as_py(), table), np.asarray(x.as_py() or [], np.int64).view(np.uint64)) for t, x in zip(b.column(1), b.column(2), strict=True)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([x.tolist() for x, _, _ in got], pa.list_(pa.int64())), pa.array([x for _, x, _ in got], pa.int64()), pa.array([x for _, _, x in got], pa.float64())], ["id", "sums", "over", "total"])

    own = texts.join(_small(wanted.select(F.col("id").alias("doc_id"))), "doc_id").select("doc_id", "text")
    alone = common.written(unshared(own), "neardup-alone")
    return own.join(alone, own["doc_id"] == alone["id"], "left").select("doc_id", "text", "alone").mapInArrow(run, "id long, sums array<long>, over long, total double")


def may_reach(similarity: float) -> str:
    """Whether a pair's greatest possible similarity, given the sums of both (the second's end in _b), reaches similarity.

    In each group the common weight is at most the lesser sum, so no pair that reaches it is ever left out; all lanes of two longs are compared at once.
    """
    high, even = 0x80808080808080, 0x00FF00FF00FF00FF
    least = f"transform(zip_with(sums, sums_b, (x, y) -> struct(x AS x, x ^ y AS d, ((x | {high}L) - y) & {high}L AS m)), v -> v.x ^ (v.d & (v.m - shiftright(v.m, 7))))"
    lanes = f"aggregate({least}, 0L, (t, v) -> t + (v & {even}L) + (shiftright(v, 8) & {even}L), t -> (t & 65535L) + (shiftright(t, 16) & 65535L) + (shiftright(t, 32) & 65535L) + shiftright(t, 48))"
    share = f"{float(similarity)}D"
    return f"least(total, total_b) >= {share} * greatest(total, total_b) - 1e-6D and ({lanes} + least(over, over_b)) * (1 + {share}) >= {UNITS} * ({share} * (total + total_b) - 1e-6D)"


def _small(df: DataFrame) -> DataFrame:
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df


def verified(texts: DataFrame, pairs: DataFrame, sizes: DataFrame, idf) -> DataFrame:
    """pairs (a, b: different documents; part_a, part_b: their components) with their similarity. Members are compared in groups of about SALT, or of
    SALT_BYTES, with a copy of a's text.

    sizes: id and size of each text.
    """
    pairs = common.written(pairs.join(sizes, pairs["b"] == sizes["id"]).select("a", "b", "part_a", "part_b", "size", F.pmod(F.xxhash64("b"), F.lit(1 << 30)).alias("salt")), "neardup-pairs")
    groups = pairs.groupBy("a").agg(F.greatest(F.ceil(F.count(F.lit(1)) / SALT), F.ceil(F.sum("size") / SALT_BYTES)).cast("int").alias("salts"), F.count(F.lit(1)).alias("n"))
    members = common.looked_up(pairs, groups, "a", "n").select("a", F.col("b").alias("doc_id"), F.expr("cast(pmod(salt, salts) as int)").alias("salt"), "part_a", "part_b")
    members = common.written(members, "neardup-members")
    # only the salts that members have, so that the centre goes nowhere else
    centres = members.select("a", F.col("a").alias("doc_id"), "salt").distinct()
    wanted = members.unionByName(centres, allowMissingColumns=True)
    found = texts.join(_small(common.written(wanted, "neardup-wanted")), "doc_id").select("a", "salt", "doc_id", "text", "part_a", "part_b")

    def compare(key, t):
        table, a = idf.value, key[0].as_py()
        ids = t["doc_id"].to_pylist()
        centre = weighted(t["text"][ids.index(a)].as_py(), table)
        at = {i: k for k, i in enumerate(ids) if i != a}
        alike = [weighted_jaccard(centre, weighted(t["text"][k].as_py(), table)) for k in at.values()]
        rows = t.take(pa.array(list(at.values()), pa.int64()))
        return pa.table({"a": rows["a"], "b": rows["doc_id"], "part_a": rows["part_a"], "part_b": rows["part_b"], "similarity": pa.array(alike, pa.float64())})

    return found.groupBy("a", "salt").applyInArrow(compare, "a long, b long, part_a long, part_b long, similarity double")


def components(edges: DataFrame) -> DataFrame:
    """id, label (the least id of its component) of every id in edges (a, b). Neither an id with many edges nor a label with many ids gathers them in one task."""
    both = common.written(edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct().withColumnRenamed("b", "id"), "neardup-edges")
    total = both.count()
    # edges are symmetric, so n is the number of both's rows with this id, too
    labels = common.written(both.groupBy("a").agg(F.least(F.col("a"), F.min("id")).alias("label"), F.count(F.lit(1)).alias("n")).withColumnRenamed("a", "id"), "neardup-labels")
    ids = labels.count()
    while True:
        near = common.looked_up(both, labels, "id", "n", total).groupBy("a").agg(F.min("label").alias("near"))
        step = common.written(labels.join(near, F.col("id") == F.col("a")).select("id", "n", F.col("label").alias("was"), F.least("label", "near").alias("label")), "neardup-step")
        shares = step.groupBy("label").agg(F.count(F.lit(1)).alias("m"))
        jump = shares.join(step.select(F.col("id").alias("to"), F.col("label").alias("next")), F.col("label") == F.col("to")).select("label", "next", "m")
        new = common.written(common.looked_up(step, jump, "label", "m", ids).select("id", "n", "was", F.least("label", "next").alias("label")), "neardup-labels")
        common.drop(labels)
        common.drop(step)
        if new.where("was <> label").isEmpty():
            return new.select("id", "label")
        labels = common.written(new.select("id", "label", "n"), "neardup-labels")
        common.drop(new)


def _ordered(pairs: DataFrame) -> DataFrame:
    end = lambda x: F.struct(F.col(x).alias("id"), F.col(f"part_{x}").alias("part"))
    pairs = pairs.select(F.least(end("a"), end("b")).alias("x"), F.greatest(end("a"), end("b")).alias("y"))
    return pairs.select(F.col("x.id").alias("a"), F.col("y.id").alias("b"), F.col("x.part").alias("part_a"), F.col("y.part").alias("part_b")).distinct()


def _merged(rows: DataFrame, links: DataFrame) -> DataFrame:
    """rows (a written table with a column part) after components that links (part_a, part_b) join have become one.

    Only components take part, so all links between two of them are one edge, however many texts both have.
    """
    joined = components(links.select(F.col("part_a").alias("a"), F.col("part_b").alias("b")))
    sizes = rows.groupBy("part").agg(F.count(F.lit(1)).alias("in_part"))
    found = common.written(sizes.join(joined, F.col("part") == F.col("id"), "left").select("part", F.coalesce("label", "part").alias("new"), "in_part"), "neardup-found")
    return common.written(common.looked_up(rows, found, "part", "in_part").drop("part", "in_part").withColumnRenamed("new", "part"), "neardup-parts")


def centred(buckets: DataFrame) -> DataFrame:
    """buckets (a written table of key, id, in_key) with each one's centre a and how well that fits: the text whose buckets have the most texts in all.

    Near copies of one text differ from each other by the edits of both. The copy with the fewest edits shares the most buckets with the others and is like the most of them.
    """
    fits = common.written(buckets.groupBy("id").agg(F.sum("in_key").alias("fit")), "neardup-fits")
    best = F.max(F.struct("fit", F.negative("id").alias("id")))
    centres = buckets.join(fits, "id").groupBy("key").agg(best.alias("best"), F.count(F.lit(1)).alias("in_key"))
    centres = common.written(centres.select("key", F.negative("best.id").alias("a"), "best.fit", "in_key"), "neardup-centres")
    return common.written(common.looked_up(buckets.drop("in_key"), centres, "key", "in_key"), "neardup-buckets")


def classes(docs: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """doc_id, copy_of (the least doc_id with an equal text), class_id (the least doc_id of its class), class_size of every row."""
    spark = docs.sparkSession
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").where("doc_id is not null")
    df, n = document_frequencies(texts)
    idf = spark.sparkContext.broadcast(idf_weights(df, n))
    sketch = common.written(sketches(texts, idf), "neardup-sketches")
    copies = sketch.groupBy("digest").agg(F.min("doc_id").alias("copy_of"), F.min(F.struct("doc_id", "size", "keys")).alias("first"), F.count(F.lit(1)).alias("n"))
    copies = common.written(copies.select("digest", F.col("copy_of").alias("id"), "first.size", "first.keys", "n"), "neardup-copies")
    sizes = copies.select("id", "size")
    rows = copies.select(F.explode("keys").alias("key"), "id")
    shared = common.written(rows.groupBy("key").agg(F.count(F.lit(1)).alias("in_key")).where("in_key > 1"), "neardup-keys")
    buckets = centred(common.written(common.looked_up(rows, shared, "key", "in_key"), "neardup-shared"))
    parts = spark.createDataFrame([], "id long, part long")
    if not buckets.isEmpty():
        alike = F.col("similarity") >= similarity
        # a pair for each text first: with the least centre of its buckets
        tried = buckets.groupBy("id").agg(F.max_by("a", F.struct("fit", F.negative("a"))).alias("a")).where("id <> a").select("a", F.col("id").alias("b"), F.col("a").alias("part_a"), F.col("id").alias("part_b"))
        done = common.written(verified(texts, tried, sizes, idf), "neardup-done")
        first_parts = components(done.where(alike))
        parts = common.written(buckets.join(first_parts, "id", "left").withColumn("part", F.coalesce("label", "id")).drop("label"), "neardup-parts")
        # then each bucket's centre with those of its members that aren't in its component yet
        heads = parts.where("id = a").select("key", F.col("part").alias("part_a"), "in_key")
        met = common.looked_up(parts.drop("in_key"), heads, "key", "in_key").where("part <> part_a")
        tried = _ordered(met.select("a", F.col("id").alias("b"), "part_a", F.col("part").alias("part_b"))).join(done, ["a", "b"], "left_anti")
        second = common.written(verified(texts, tried, sizes, idf), "neardup-done")
        parts = _merged(parts.select("key", "id", "part"), second.where(alike))
        open_ = parts.groupBy("key").agg(F.min("part").alias("lo"), F.max("part").alias("hi"), F.count(F.lit(1)).alias("in_key")).where("lo < hi").select("key", "in_key")
        rest = common.looked_up(parts, open_, "key", "in_key").groupBy("id").agg(F.min("part").alias("part"), F.collect_list("key").alias("in_keys"))
        # a row for each text, however many open buckets it has: what is joined to it comes once
        rest = common.written(rest, "neardup-open")
        sums = common.written(signatures(texts, rest.select("id"), idf), "neardup-sums")
        rest = rest.join(sums.join(copies.select("id", "keys"), "id"), "id")
        rest = common.written(rest.withColumn("key", F.explode("in_keys")).drop("in_keys").withColumn("band", F.array_position("keys", F.col("key"))), "neardup-rest")
        other = rest.select("key", F.col("id").alias("b"), F.col("part").alias("part_b"), F.col("sums").alias("sums_b"), F.col("over").alias("over_b"), F.col("total").alias("total_b"), F.col("keys").alias("keys_b"))
        # two texts that share several buckets are a pair in the first of them only
        first = "band = array_position(zip_with(keys, keys_b, (x, y) -> x = y), true)"
        met = rest.withColumnRenamed("id", "a").join(other.withColumnRenamed("key", "key_b"), F.expr(f"key = key_b and part < part_b and {first} and {may_reach(similarity)}"))
        new = _ordered(met.select("a", "b", F.col("part").alias("part_a"), "part_b")).join(done.unionByName(second), ["a", "b"], "left_anti")
        more = common.written(verified(texts, new, sizes, idf).where(alike), "neardup-links")
        parts = _merged(common.written(parts.select("id", "part").distinct(), "neardup-ids"), more)
    copies = common.written(copies.select("digest", "id", "n").join(parts, "id", "left").select("digest", "id", "n", F.coalesce("part", "id").alias("class_id")), "neardup-copies")
    totals = copies.groupBy("class_id").agg(F.sum("n").alias("class_size"), F.count(F.lit(1)).alias("texts"))
    copies = common.written(common.looked_up(copies, totals, "class_id", "texts").select("digest", F.col("id").alias("copy_of"), "class_id", "class_size", "n"), "neardup-classes")
    return common.looked_up(sketch.select("doc_id", "digest"), copies, "digest", "n").select("doc_id", "copy_of", "class_id", "class_size")


def op2_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classes(common.table(spark, sf_dir, "documents"))
