"""Quality scores by Bradley-Terry ranking.

A document's score is linear in features of its text: shares and counts, and its words and character 4-grams, hashed to GRAMS cells each. Preference pairs (a document labelled 1, one labelled 0) say which
of two is better, and the weights maximise the likelihood that a logistic curve gives to the differences of their scores. The cut is a
quantile of the training documents' scores, the share that is labelled 0; a second logistic curve around it maps
scores to 0..1, so that predicted = 1 means a score of at least one half.

Only the text is used. The weights' fit takes at most SAMPLE different rows of each label, those with the smallest hashes, and PAIRS
pairs for each row of the more frequent label: a bounded sample on the driver, where each value has 16 bits. The cut and the slope come from all training rows,
by counts and sums that the executors make. Scores cover every row and whole text. Null text counts as empty;
repeated doc_ids are scored row by row, and so are rows without one, which aren't held out and have no label. Of labels of one doc_id that differ, 0 counts.
Where a label has no row, all scores are 1; an empty table gives no rows. A text's features take time and memory in proportion to its length.
"""

from __future__ import annotations

import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common, dedup

#: Training rows of each label at most that the weights are fitted on, and how many pairs each row is in.
SAMPLE, PAIRS = 20_000, 4
PENALTY = 1e-4
#: Cells that words are hashed to, and as many for character 4-grams; bytes of a text that are counted at once.
GRAMS, BLOCK = 256, 1 << 20
#: Ranges of scores that one pass of quantile() counts.
BINS = 4096

_LETTERS = bytes([*range(65, 91), *range(97, 123), *range(128, 256)])
_UPPER = bytes(range(65, 91))
_DIGITS = bytes(range(48, 58))
_SPACE = b" \t\n\r\x0b\x0c"
_STOPS = b".,;:!?"
_OTHER = bytes(b for b in range(33, 127) if b not in _LETTERS + _DIGITS + _STOPS)

FEATURES = (
    "log_bytes", "letters", "upper", "digits", "spaces", "stops", "marks", "word_bytes", "long_words", "kinds_of_words", "kinds_of_lines",
    "lines_again", "line_words", "marked_words", "ends_marked", "bars", "squeeze", *(f"{kind}_{i}" for kind in ("word", "gram") for i in range(GRAMS)),
)
SHARES = len(FEATURES) - 2 * GRAMS


def grams(b: bytes, words: Counter) -> np.ndarray:
    """Square roots of the shares that each cell has of all words, then of all 4-grams of bytes."""
    out = np.zeros((2, GRAMS))
    at = np.fromiter((zlib.crc32(w) % GRAMS for w in words), np.int64, len(words))
    out[0] = np.bincount(at, np.fromiter(words.values(), float, len(words)), GRAMS)
    for k in range(0, len(b) - 3, BLOCK):
        x = np.frombuffer(b, np.uint8, min(BLOCK + 3, len(b) - k), k).astype(np.uint32)
        key = (x[:-3] | x[1:-2] << 8 | x[2:-1] << 16 | x[3:] << 24) * np.uint32(2654435761)
        out[1] += np.bincount((key >> np.uint32(24)).astype(np.int64) % GRAMS, minlength=GRAMS)
    return np.sqrt(out / np.maximum(out.sum(1, keepdims=True), 1)).reshape(-1)


def features(text: str | None) -> np.ndarray:
    """Shares and logs of the whole text, then its grams, each bounded."""
    b = (text or "").encode()
    n = len(b) or 1
    share = lambda chars: (len(b) - len(b.translate(None, chars))) / n
    words = b.split()
    kinds = Counter(words)
    w = len(words) or 1
    lines = [x for x in b.split(b"\n") if x.strip()]
    k = len(lines) or 1
    marked = sum(1 for x in words if x[-1] in _OTHER)
    inner = sum(1 for x in words if not x.isalnum() and x.strip(_STOPS).translate(None, _LETTERS))
    shares = [
        np.log1p(len(b)) / 10, share(_LETTERS), share(_UPPER), share(_DIGITS), share(_SPACE), share(_STOPS), share(_OTHER), min(n / w, 50) / 10,
        sum(1 for x in words if len(x) > 20) / w, len(kinds) / w, len(set(lines)) / k, 1 - sum(map(len, set(lines))) / max(1, sum(map(len, lines))),
        np.log1p(w / k) / 5, inner / w, marked / w, kinds[b"|"] / w, min(2.0, len(zlib.compress(b, 1)) / n),
    ]
    return np.concatenate([shares, grams(b, kinds)])


def _wanted(docs: DataFrame, labels: DataFrame, held: int | None) -> DataFrame:
    """Training rows: doc_id, text, label. held: the remainder of crc32(doc_id) mod 3 that is left out."""
    kept = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("label")).where("label in (0, 1) and doc_id is not null")
    kept = kept.groupBy("doc_id").agg(F.min("label").alias("label"))
    if held is not None:
        kept = kept.where(F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(3)) != held)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(dedup._small(kept), "doc_id")


def _sigmoid(x):
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))


def fit(x: np.ndarray, y: np.ndarray, seed: int = 7, steps: int = 300) -> dict:
    """Weights by gradient steps with momentum over all preference pairs. The grams of a kind together vary as much as one share does, so that many rare cells don't outweigh it."""
    if len(set(y.tolist())) < 2:
        return {"mean": np.zeros(x.shape[1]), "weights": np.zeros(x.shape[1])}
    z = x.astype(np.float32)  # all else goes in place or by column
    mean = z.mean(0, dtype=float)
    z -= mean.astype(np.float32)
    scale = np.sqrt(np.einsum("ij,ij->j", z, z, dtype=float) / len(z)) + 1e-6
    scale[SHARES:] *= GRAMS**0.5
    z /= scale.astype(np.float32)
    good, bad = np.flatnonzero(y == 1), np.flatnonzero(y == 0)
    rng = np.random.default_rng(seed)
    a = np.concatenate([rng.permutation(np.resize(good, max(len(good), len(bad)))) for _ in range(PAIRS)])
    b = np.concatenate([rng.permutation(np.resize(bad, max(len(good), len(bad)))) for _ in range(PAIRS)])
    w, speed = np.zeros(x.shape[1], np.float32), np.zeros(x.shape[1], np.float32)
    for _ in range(steps):
        s = z @ w
        p = _sigmoid(s[b] - s[a])
        pull = (np.bincount(a, p, len(z)) - np.bincount(b, p, len(z))) / len(a)  # a pair pulls its two rows apart
        speed = 0.9 * speed + pull.astype(np.float32) @ z - PENALTY * w
        w = w + 0.4 * speed
    return {"mean": mean, "weights": w / scale}


def _linear(x: np.ndarray, model: dict) -> np.ndarray:
    return ((x - model["mean"]) * model["weights"]).sum(-1)


def quantile(rows: DataFrame, share: float) -> float:
    """The exact quantile of the column s, between neighbours as numpy's: counts of BINS ranges, then of the one with its rank, until that holds one value."""
    n, lo, hi = rows.agg(F.count("s"), F.min("s"), F.max("s")).first()
    at = (n - 1) * share
    rank, after = int(at), hi
    while lo < hi:
        bin_ = F.least(F.floor((F.col("s") - lo) / ((hi - lo) / BINS)), F.lit(BINS - 1))
        parts = rows.where(F.col("s").between(lo, hi)).groupBy(bin_.alias("bin")).agg(F.count("s").alias("n"), F.min("s").alias("lo"), F.max("s").alias("hi")).orderBy("bin").collect()
        k = 0
        while rank >= parts[k]["n"]:
            rank -= parts[k]["n"]
            k += 1
        after = parts[k + 1]["lo"] if k + 1 < len(parts) else after
        lo, hi, n = parts[k]["lo"], parts[k]["hi"], parts[k]["n"]
    return lo + (at - int(at)) * ((lo if rank + 1 < n else after) - lo)


def curve(rows: DataFrame) -> dict:
    """The cut and the slope around it, from s and label of all training rows. The slope alone is fitted, so that the quantile stays at one half."""
    n, bad = rows.agg(F.count("s"), F.sum(F.lit(1) - F.col("label"))).first()
    if not 0 < (bad or 0) < n:
        return {"cut": -40.0, "slope": 1.0}
    cut = quantile(rows, bad / n)
    slopes = np.geomspace(0.05, 20, 60)
    t = (F.col("s") - cut) * (F.lit(1) - 2 * F.col("label"))
    loss = rows.select(t.alias("t")).agg(*[F.avg(F.log1p(F.exp(F.greatest(F.least(F.col("t") * float(k), F.lit(40.0)), F.lit(-40.0))))) for k in slopes]).first()
    return {"cut": cut, "slope": float(slopes[int(np.argmin(list(loss)))])}


KINDS = (pa.int32(), pa.int64(), pa.binary())


def sample(rows: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Features and labels of the SAMPLE different rows of each label whose hashes are smallest; rows is doc_id, text, label."""
    hashed = rows.select("text", "label", F.xxhash64("doc_id", "text").alias("h"))
    few = hashed.select("label", "h").distinct()
    few = [few.where(F.col("label") == v).orderBy("h").limit(SAMPLE).agg(F.max("h")).first()[0] for v in (0, 1)]

    def run(batches):
        seen = set()  # at most 2 * SAMPLE, so a row that is repeated any number of times leaves a task once
        for b in batches:
            out = []
            for text, *key in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if tuple(key) not in seen:
                    seen.add(tuple(key))
                    out.append((*key, np.float16(features(text)).tobytes()))
            yield pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(zip(*out, strict=True), KINDS, strict=True)] if out else [pa.array([], t) for t in KINDS], ["label", "h", "x"])

    chosen = [hashed.where((F.col("label") == v) & (F.col("h") <= F.lit(top))) for v, top in enumerate(few) if top is not None]
    if len(chosen) < 2:
        return np.zeros((0, len(FEATURES)), np.float16), np.zeros(0, int)
    got = chosen[0].unionByName(chosen[1]).mapInArrow(run, "label int, h long, x binary").groupBy("label", "h").agg(F.first("x").alias("x"))
    got = got.toArrow().sort_by([("label", "ascending"), ("h", "ascending")])
    x = np.empty((len(got), len(FEATURES)), np.float16)
    for i, v in enumerate(got["x"]):
        x[i] = np.frombuffer(v.as_buffer(), np.float16)
    return x, got["label"].to_numpy()


def train(docs: DataFrame, labels: DataFrame, held: int | None = None) -> dict:
    rows = _wanted(docs, labels, held)
    model = fit(*sample(rows))

    def linear(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array(_scores(b.column(0), model)), b.column(1)], ["s", "label"])

    scored = common.written(rows.select("text", "label").mapInArrow(linear, "s double, label int"), "quality-scores")
    model |= curve(scored)
    common.drop(scored)
    return model


def _scores(texts: pa.Array, model: dict) -> np.ndarray:
    """One text's features at a time."""
    return np.array([_linear(features(t.as_py()), model) for t in texts], float)


def score(docs: DataFrame, model: dict, names: tuple[str, str] = ("score", "predicted")) -> DataFrame:
    """docs with two more columns: the score and whether it is at least one half. Earlier columns of these names are replaced."""
    kept = [c for c in docs.columns if c.lower() not in names]
    at = kept.index("text")
    schema = docs.select(*kept).withColumns({names[0]: F.lit(0.0), names[1]: F.lit(0)}).schema

    def run(batches):
        for b in batches:
            s = _sigmoid((_scores(b.column(at), model) - model["cut"]) * model["slope"])
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(s), pa.array((s >= 0.5).astype("int32"))], [*kept, *names])

    return docs.select(*kept).mapInArrow(run, schema)


def op3_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    model = train(docs, common.table(spark, sf_dir, "labels"), held=1)
    held = F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(3)) == 1, F.lit(False))
    return score(docs.select("doc_id", "text"), model).select("doc_id", held.alias("held_out"), "score", "predicted")
