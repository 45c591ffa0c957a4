"""URL filter: rules first, then a log-likelihood ratio of two character models.

Rules (host and subdomains, path prefix; the longest wins) decide the urls they fit, and those verdicts are the training
labels: one variable-order Markov model is counted over accepted urls, one over rejected ones. Characters are mapped to
an alphabet of SIZE symbols, so a model is a dense table of SIZE**(CONTEXT+1) counts whatever the input's size; shorter
contexts are its marginals, mixed in by Witten-Bell smoothing. A url's score is the difference of the two log-likelihoods over
its length. A fifth of the labelled urls is kept out of the counts and calibrates the score to a probability; other
urls are allowed if it is at least one half.

The alphabet is reduced so that the tables stay small: all digits are one symbol, all other marks and bytes above ASCII another, and letters lose their
case. Urls that differ in these only have equal scores.

Repeated rows are judged one by one; pages' other columns are ignored; an empty table gives no rows; a url of any length is scored whole.
Null urls and urls without :// have an empty host and path, fit no rule and are scored as they are (null as empty). Where one
class has no labelled url the score is 0 for all, and urls without a rule are allowed.
"""

from __future__ import annotations

import string

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: action and rule (host, then path), fixed values of the query.
RULES = (("block", "com/en/"), ("allow", "example.com/en/7"), ("allow", "net/de/"), ("block", "example.net/de/8"), ("block", "org/es/"))

MARKS = "./-?=&%_#:~"
SIZE, CONTEXT = 40, 3
BINS, SPAN = 2000, 10.0
#: Kept out of the counts, for calibration: labelled urls whose hash leaves this remainder mod 5.
HELD = 0


def _symbols() -> np.ndarray:
    """Byte to symbol: letters of either case 1 to 26, digits 27, marks from 28, others SIZE - 1; 0 stands around the url."""
    table = np.full(256, SIZE - 1, np.int64)
    for i, c in enumerate(string.ascii_lowercase):
        table[ord(c)] = table[ord(c.upper())] = 1 + i
    table[[ord(c) for c in string.digits]] = 27
    for i, c in enumerate(MARKS):
        table[ord(c)] = 28 + i
    return table


def grams(url: str | None, table: np.ndarray) -> np.ndarray:
    """The cell of each character and of the end, with its context, in a flat count table."""
    s = np.concatenate([np.zeros(CONTEXT, np.int64), table[np.frombuffer((url or "").encode(), np.uint8)], [0]])
    out = s[: len(s) - CONTEXT].copy()
    for k in range(1, CONTEXT + 1):
        out = out * SIZE + s[k : len(s) - CONTEXT + k]
    return out


def smoothed(counts: np.ndarray) -> np.ndarray:
    """Probability of each symbol after each context of CONTEXT symbols: Witten-Bell from the longest context down to uniform."""
    n = counts.reshape((SIZE,) * (CONTEXT + 1)).astype(np.float64)
    p = np.full(SIZE, 1.0 / SIZE)
    for k in range(CONTEXT + 1):
        part = n.sum(axis=tuple(range(CONTEXT - k)))
        total, kinds = part.sum(-1, keepdims=True), (part > 0).sum(-1, keepdims=True)
        p = np.where(total > 0, (part + kinds * p) / np.maximum(total + kinds, 1), p)
    return p.reshape(-1)


def parsed(url: str = "url") -> tuple[Column, Column]:
    """host and path."""
    at = F.instr(F.col(url), "://")
    rest = F.expr(f"substring(`{url}`, instr(`{url}`, '://') + 3)")
    host = F.regexp_extract(rest, r"^[^/?#]*", 0)
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    none = F.col(url).isNull() | (at == 0)
    return F.when(none, "").otherwise(F.translate(host, string.ascii_uppercase, string.ascii_lowercase)), F.when(none, "").otherwise(path)


def rule_of(rules, host: str = "host", path: str = "path") -> Column:
    """The longest rule that fits, else null; rules are a short list given by the caller."""
    fits = []
    for _, rule in sorted(rules, key=lambda r: (-len(r[1]), r[1])):
        h, p = rule.split("/", 1)
        fits.append(F.when(((F.col(host) == h) | F.col(host).endswith("." + h)) & F.col(path).startswith("/" + p), F.lit(rule)))
    return F.coalesce(*fits, F.lit(None).cast("string"))


def count_models(labelled: DataFrame) -> np.ndarray:
    """Counts (2, SIZE**(CONTEXT+1)) over all rows of url, label (1 accepted, 0 rejected). At most that many cells reach the driver."""
    cells = SIZE ** (CONTEXT + 1)

    def run(batches):
        table, sums = _symbols(), {}
        for b in batches:
            for label, url in zip(b.column(1).to_pylist(), b.column(0).to_pylist(), strict=True):
                at, n = np.unique(grams(url, table) + label * cells, return_counts=True)
                for k, v in zip(at.tolist(), n.tolist(), strict=True):
                    sums[k] = sums.get(k, 0) + v
        if sums:
            yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int64()), pa.array(list(sums.values()), pa.int64())], ["cell", "n"])

    out = np.zeros(2 * cells)
    got = labelled.select("url", "label").mapInArrow(run, "cell long, n long").groupBy("cell").agg(F.sum("n").alias("n")).toArrow()
    out[got["cell"].to_numpy()] = got["n"].to_numpy()
    return out.reshape(2, cells)


def scored(pages: DataFrame, ratio, url: str = "url") -> DataFrame:
    """pages with `score`: mean log ratio of its characters. ratio is a broadcast float32 table of fixed size."""
    names = pages.columns
    schema = pages.withColumn("score", F.lit(0.0)).schema

    def run(batches):
        table, r = _symbols(), ratio.value
        for b in batches:
            s = [float(r[grams(u, table)].mean(dtype=np.float64)) for u in b.column(names.index(url)).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(s, pa.float64())], [*names, "score"])

    return pages.mapInArrow(run, schema)


def calibrate(bins: list[tuple[int, int, int]]) -> tuple[float, float]:
    """Slope and offset of a logistic curve through (bin, label, rows), by Newton's method with a small penalty; (1, 0) without both labels."""
    x = np.array([(b + 0.5) * 2 * SPAN / BINS - SPAN for b, _, _ in bins])
    y, w = np.array([v for _, v, _ in bins], float), np.array([n for _, _, n in bins], float)
    if len(set(y)) < 2:
        return 1.0, 0.0
    f, t = np.stack([x, np.ones_like(x)], 1), np.array([1.0, 0.0])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(f @ t, -30, 30)))
        g = f.T @ (w * (p - y)) + 1e-2 * (t - np.array([1.0, 0.0]))
        step = np.linalg.solve((f * (w * p * (1 - p))[:, None]).T @ f + 1e-2 * np.eye(2), g)
        t = t - np.clip(step, -5, 5)
        if np.abs(step).max() < 1e-9:
            break
    return float(t[0]), float(t[1])


def filter_urls(pages: DataFrame, rules=RULES) -> DataFrame:
    """page_id, host, path, rule, verdict, score (log ratio per character) and accepted (its calibrated probability)."""
    spark = pages.sparkSession
    host, path = parsed()
    rows = pages.select("page_id", "url").withColumns({"host": host, "path": path}).withColumn("rule", rule_of(rules))
    allow = [r for a, r in rules if a == "allow"]
    by_rule = F.when(F.col("rule").isin(allow), 1).when(F.col("rule").isNotNull(), 0)
    held = F.pmod(F.xxhash64("url"), F.lit(5)) == HELD
    labelled = rows.select("url", by_rule.alias("label"), held.alias("held")).where("label is not null")
    counts = count_models(labelled.where("not held"))
    rejected, accepted = (smoothed(c) for c in counts)
    ratio = np.log(accepted / rejected).astype(np.float32) if counts.any(axis=1).all() else np.zeros(counts.shape[1], np.float32)
    shared = spark.sparkContext.broadcast(ratio)
    at = F.least(F.greatest(F.floor((F.col("score") + SPAN) * BINS / (2 * SPAN)), F.lit(0)), F.lit(BINS - 1))
    bins = scored(labelled.where("held"), shared).groupBy(at.alias("bin"), "label").count().collect()
    slope, offset = calibrate([(r["bin"], r["label"], r["count"]) for r in bins])
    out = scored(rows, shared).withColumn("accepted", 1 / (1 + F.exp(-(F.col("score") * slope + offset))))
    verdict = F.when(by_rule == 1, "allow").when(by_rule == 0, "block").when(F.col("accepted") >= 0.5, "allow").otherwise("block")
    return out.select("page_id", "host", "path", "rule", verdict.alias("verdict"), "score", "accepted")


def op7_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return filter_urls(common.table(spark, sf_dir, "pages"), RULES)
