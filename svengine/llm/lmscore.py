"""Language-model scores from n-gram counts in log-frequency Bloom filters.

Tokens are words (ASCII lower case, split at ASCII white space) and an end token; keys are hashes of words (63 bits) and of word pairs
(48 bits). Training: each task counts the keys of about STEP_TOKENS tokens at a time and sends them, sorted and packed, a row for each range
of keys that it has any in. The task of a range sums them. Words' counts are kept as they are. Pairs' counts are quantised and inserted into a
log-frequency Bloom filter (a key is inserted once for each level up to its own); the filter is all that is kept of them. The model is this
table: one row of bounded size for each range.

Scoring: documents are dealt to blocks of about BLOCK_BYTES. A block sends its distinct keys to the ranges, where the model's row answers them, pairs by
repeated membership probes, level by level until one fails; the block then scores its documents. The filter grows with the corpus, so it isn't broadcast as
a whole: probes come to its parts. Rows sent are never more than the distinct keys of the blocks, however many blocks there are.

P(w | v) = (1 - mix) * P(w) + mix * c(v w) / c(v), with P(w) = (c(w) + 0.5) / (N + 0.5 (V + 1)); without training counts of v it is P(w).
mix is the value of MIXES that gives the training texts the greatest leave-one-out likelihood. Null text: the end token only.
Rows with the same doc_id, and rows without one, are scored one by one; other columns are ignored; an empty table gives no rows. A text is scored by
one task, whatever its length.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

BLOCK_BYTES = 16_000_000
BASE = 1.5
BITS_PER_ENTRY, HASHES = 12, 8
MIXES = (0.0, 0.02, 0.05, 0.1, 0.2, 0.4)
WORD_BITS, PAIR_BITS = 63, 48

_M = np.uint64(0x9E3779B97F4A7C15)
_END = xxhash.xxh64_intdigest(b"\n")  # no word holds white space


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


def token_hashes(text: str | None) -> np.ndarray:
    """Of the words and the end token, 63 bits each."""
    words = (text or "").encode().lower().split()
    out = np.empty(len(words) + 1, np.uint64)
    out[:-1] = np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))
    out[-1] = _END
    return out >> np.uint64(64 - WORD_BITS)


def pair_hashes(h: np.ndarray) -> np.ndarray:
    """Of each token with the one before it; the first follows an end token."""
    before = np.concatenate([h[-1:], h[:-1]])
    return _mixed(before * _M + h) >> np.uint64(64 - PAIR_BITS)


def quantised(counts: np.ndarray) -> np.ndarray:
    """Level of each count: 0 for none, then 1 + floor of the logarithm to BASE."""
    return np.where(counts > 0, 1 + np.floor(np.log(np.maximum(counts, 1)) / np.log(BASE) + 1e-9), 0).astype(np.int64)


def level_values(levels: int = 80) -> np.ndarray:
    """The count that a level stands for: the middle of the counts that have it."""
    lo = np.ceil(BASE ** (np.arange(levels) - 1.0) - 1e-9)
    hi = np.ceil(BASE ** np.arange(levels) - 1e-9) - 1
    out = (lo + np.maximum(lo, hi)) / 2
    out[0] = 0
    return out


class LogFrequencyBloom:
    """A Bloom filter of (key, level) entries: level(key) probes levels from 1 up until one is missing, and is never too low."""

    def __init__(self, keys: np.ndarray, counts: np.ndarray):
        q = quantised(counts)
        self.m = np.uint64(max(64, -(-int(q.sum()) * BITS_PER_ENTRY // 8) * 8))
        bits = np.zeros(int(self.m), bool)
        for level in range(1, int(q.max(initial=0)) + 1):
            for at in self._places(keys[q >= level], level):
                bits[at] = True
        self.bits = np.packbits(bits, bitorder="little")

    @classmethod
    def of(cls, bits: bytes) -> LogFrequencyBloom:
        """The filter whose bits were kept."""
        out = cls.__new__(cls)
        out.bits = np.frombuffer(bits, np.uint8)
        out.m = np.uint64(8 * len(out.bits))
        return out

    def _places(self, keys: np.ndarray, level: int):
        a = _mixed(keys * _M + np.uint64(level))
        b = _mixed(a + _M) | np.uint64(1)
        for i in range(HASHES):
            yield (a + np.uint64(i) * b) % self.m

    def level(self, keys: np.ndarray) -> np.ndarray:
        out = np.zeros(len(keys), np.uint8)
        left = np.arange(len(keys))
        level = 1
        while len(left) and level < 80:
            for at in self._places_of(keys, left, level):
                hit = (self.bits[at >> np.uint64(3)] >> (at & np.uint64(7)).astype(np.uint8)) & 1
                left = left[hit == 1]
                if not len(left):
                    break
            out[left] = level
            level += 1
        return out

    def _places_of(self, keys, left, level):
        """As _places, for what is still left after each probe; the caller's `left` shrinks, so hashes are kept by position."""
        a = _mixed(keys[left] * _M + np.uint64(level))
        b = _mixed(a + _M) | np.uint64(1)
        alive = np.arange(len(left))
        for i in range(HASHES):
            at = (a[alive] + np.uint64(i) * b[alive]) % self.m
            yield at
            hit = (self.bits[at >> np.uint64(3)] >> (at & np.uint64(7)).astype(np.uint8)) & 1
            alive = alive[hit == 1]


def _packed(x: np.ndarray, width: int) -> bytes:
    """The lowest bytes of each value, by significance, compressed."""
    planes = x.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width].T
    return zstandard.ZstdCompressor(level=1).compress(np.ascontiguousarray(planes).tobytes())


def _unpacked(b: bytes, width: int) -> np.ndarray:
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(b), np.uint8).reshape(width, -1)
    out = np.zeros((planes.shape[1], 8), np.uint8)
    out[:, :width] = planes.T
    return out.reshape(-1).view("<u8")


def _distinct(keys: np.ndarray) -> np.ndarray:
    """Sorted distinct keys, by a plain sort: numpy's unique goes through a hash table that misses the caches."""
    k = np.sort(keys)
    return k[np.concatenate([[True], k[1:] != k[:-1]])] if len(k) else k


def _tokens(t: pa.Table):
    """Documents' positions and their tokens: (document of each token, word hashes, pair hashes)."""
    hashes = [token_hashes(x.as_py()) for x in t["text"]]
    n = np.array([len(h) for h in hashes])
    return n, np.repeat(np.arange(len(n)), n), np.concatenate(hashes), np.concatenate([pair_hashes(h) for h in hashes])


KINDS = (("word", WORD_BITS), ("pair", PAIR_BITS))
#: Tokens that a training task counts at a time.
STEP_TOKENS = 1 << 21
COUNTS = "kind string, span long, keys binary, counts binary"
PART = "kind string, span long, keys binary, filter binary, tokens long, types long"
ASKED = "kind string, span long, block long, keys binary"
ANSWER = "kind string, span long, block long, answer binary"


def _spans(keys: np.ndarray, bits: int, spans: int) -> np.ndarray:
    """Range of each key; ascending keys have ascending ranges."""
    return np.minimum((keys.astype(np.float64) * (spans / 2.0**bits)).astype(np.int64), spans - 1)


def _cut(k: np.ndarray, bits: int, spans: int):
    """(range, first, last) of each range that sorted keys have any in."""
    s = _spans(k, bits, spans)
    edges = np.flatnonzero(np.concatenate([[True], s[1:] != s[:-1], [True]])) if len(k) else np.zeros(1, int)
    return zip(s[edges[:-1]].tolist(), edges[:-1].tolist(), edges[1:].tolist(), strict=True)


def train(texts: DataFrame, spans: int) -> DataFrame:
    """The model: for each kind and range of keys the keys with counts (words) or the filter (pairs), and sums over the range."""

    def count(batches):
        def rows(held):
            hashes = [token_hashes(t) for t in held]
            for (kind, bits), keys in zip(KINDS, (np.concatenate(hashes), np.concatenate([pair_hashes(h) for h in hashes])), strict=True):
                k, c = np.unique(keys, return_counts=True)
                yield from ((kind, span, _packed(np.diff(k[lo:hi], prepend=np.uint64(0)), 8), _packed(c[lo:hi], 4)) for span, lo, hi in _cut(k, bits, spans))

        def emit(held):
            out = list(rows(held))
            return pa.RecordBatch.from_arrays([pa.array([r[0] for r in out]), pa.array([r[1] for r in out], pa.int64()), pa.array([r[2] for r in out], pa.binary()), pa.array([r[3] for r in out], pa.binary())], ["kind", "span", "keys", "counts"])

        held, n = [], 0
        for b in batches:
            for t in b.column(0):
                held.append(t.as_py() or "")
                n += len(held[-1]) // 6 + 1
                if n >= STEP_TOKENS:
                    yield emit(held)
                    held, n = [], 0
        if held:
            yield emit(held)

    def keep(key, t):
        kind, span = key[0].as_py(), key[1].as_py()
        parts = [np.cumsum(_unpacked(x.as_py(), 8), dtype=np.uint64) for x in t["keys"]]
        counts = np.concatenate([_unpacked(x.as_py(), 4) for x in t["counts"]]).astype(np.int64)
        k = np.concatenate(parts)
        order = np.argsort(k, kind="stable")
        k, counts = k[order], counts[order]
        first = np.flatnonzero(np.concatenate([[True], k[1:] != k[:-1]]))
        k, counts = k[first], np.add.reduceat(counts, first)
        if kind == "word":
            blob = (_packed(np.diff(k, prepend=np.uint64(0)), 8), _packed(counts, 6))
        else:
            bloom = LogFrequencyBloom(k, counts)
            blob = (None, bloom.bits.tobytes())
        return pa.table({"kind": [kind], "span": pa.array([span], pa.int64()), "keys": pa.array([blob[0]], pa.binary()), "filter": pa.array([blob[1]], pa.binary()), "tokens": pa.array([int(counts.sum())], pa.int64()), "types": pa.array([len(k)], pa.int64())})

    return texts.select("text").mapInArrow(count, COUNTS).groupBy("kind", "span").applyInArrow(keep, PART)


def _answers(docs: DataFrame, model: DataFrame, spans: int) -> DataFrame:
    def ask(key, t):
        block = key[0].as_py()
        _, _, words, pairs = _tokens(t)
        out = [(kind, span, block, _packed(np.diff(k[lo:hi], prepend=np.uint64(0)), 8)) for (kind, bits), k in zip(KINDS, (_distinct(words), _distinct(pairs)), strict=True) for span, lo, hi in _cut(k, bits, spans)]
        return pa.table({"kind": [r[0] for r in out], "span": pa.array([r[1] for r in out], pa.int64()), "block": pa.array([r[2] for r in out], pa.int64()), "keys": pa.array([r[3] for r in out], pa.binary())})

    def answer(key, asked, model):
        if not asked.num_rows:
            return pa.table({"kind": pa.array([], pa.string()), "span": pa.array([], pa.int64()), "block": pa.array([], pa.int64()), "answer": pa.array([], pa.binary())})
        kind, row = asked["kind"][0].as_py(), model.to_pylist()[0] if model.num_rows else None
        bloom = LogFrequencyBloom.of(row["filter"]) if row and kind == "pair" else None
        known = np.cumsum(_unpacked(row["keys"], 8), dtype=np.uint64) if row and kind == "word" else None
        total = _unpacked(row["filter"], 6) if known is not None else None

        def one(keys):
            if kind == "pair":
                return _packed(bloom.level(keys) if row else np.zeros(len(keys), np.uint8), 1)
            if not row:
                return _packed(np.zeros(len(keys), np.uint64), 6)
            at = np.minimum(np.searchsorted(known, keys), len(known) - 1)
            return _packed(np.where(known[at] == keys, total[at], 0), 6)

        blobs = [one(np.cumsum(_unpacked(x.as_py(), 8), dtype=np.uint64)) for x in asked["keys"]]
        return pa.table({"kind": asked["kind"], "span": asked["span"], "block": asked["block"], "answer": pa.array(blobs, pa.binary())})

    asked = docs.groupBy("block").applyInArrow(ask, ASKED)
    return asked.groupBy("kind", "span").cogroup(model.select("kind", "span", "keys", "filter").groupBy("kind", "span")).applyInArrow(answer, ANSWER)


def scores(docs: DataFrame, held: int = 1, folds: int = 5, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, mix of every row; rows of the fold `held` aren't learnt from."""
    spark = docs.sparkSession
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks = size // block_bytes + 1
    held_out = F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(folds)) == held, F.lit(False))
    dealt = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", held_out.alias("held_out"), F.pmod(F.xxhash64("doc_id", "text"), F.lit(blocks)).alias("block"))
    model = common.written(train(dealt.where("not held_out"), blocks), "lm-model")
    answers = common.written(_answers(dealt, model, blocks), "lm-answers")
    sums = model.where("kind = 'word'").agg(F.sum("tokens"), F.sum("types")).first()
    n, types = sums[0] or 0, sums[1] or 0
    whole = n + 0.5 * (types + 1)
    value = level_values()

    def score(key, left, right):
        t = left.combine_chunks()
        length, doc, words, pairs = _tokens(t)
        order = right.sort_by([("kind", "ascending"), ("span", "ascending")])
        kinds = order["kind"].to_pylist()
        got = lambda kind, width: np.concatenate([_unpacked(x.as_py(), width) for x, k in zip(order["answer"], kinds, strict=True) if k == kind])
        lookup = lambda keys, found: found[np.searchsorted(_distinct(keys), keys)]
        c = lookup(words, got("word", 6)).astype(np.float64)
        cp = value[lookup(pairs, got("pair", 1)).astype(np.int64)]
        last = np.cumsum(length) - 1
        before = np.concatenate([[0.0], c[:-1]])
        before[last - length + 1] = c[last]
        per_doc = lambda v: np.bincount(doc, weights=v, minlength=len(length))
        p, less = (c + 0.5) / whole, (np.maximum(c - 1, 0) + 0.5) / max(whole - 1, 0.5)
        pp = np.where(before > 0, np.minimum(cp / np.maximum(before, 1), 1), p)
        left_out = np.where(before > 1, np.minimum(np.maximum(cp - 1, 0) / np.maximum(before - 1, 1), 1), less)
        grid = [per_doc(np.log10((1 - x) * p + x * pp)) for x in MIXES]
        out = t["held_out"].to_pylist()
        train = ~np.array(out, bool)
        loo = [per_doc(np.log10((1 - x) * less + x * left_out)) * train for x in MIXES]
        lists = lambda g: pa.array(np.stack(g, 1).tolist(), pa.list_(pa.float64()))
        return pa.table({"doc_id": t["doc_id"], "held_out": out, "n_tokens": pa.array(length, pa.int64()), "n_known": pa.array(per_doc(c > 0).astype(np.int64)), "base_score": grid[0], "grid": lists(grid), "loo": lists(loo)})

    kind = "doc_id long, held_out boolean, n_tokens long, n_known long, base_score double, grid array<double>, loo array<double>"
    rows = common.written(dealt.groupBy("block").cogroup(answers.groupBy("block")).applyInArrow(score, kind), "lm-scores")
    likelihood = rows.agg(*[F.sum(F.col("loo")[i]).alias(f"m{i}") for i in range(len(MIXES))]).first()
    best = max(range(len(MIXES)), key=lambda i: likelihood[i] or 0.0)
    return rows.select("doc_id", "held_out", "n_tokens", "n_known", F.lit(int(n)).cast("long").alias("train_tokens"), "base_score", F.col("grid")[best].alias("score"), F.lit(MIXES[best]).alias("mix"))


def op10_lm_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scores(common.table(spark, sf_dir, "documents")).drop("mix")
