"""Encoding and decoding of whole texts by forced-boundary splitting (see tokens.py), as an Arrow map without a shuffle.

Null text counts as empty (no ids). Equal rows give equal results, rows without a doc_id are encoded as others; other columns of the input are ignored; an
empty table gives no rows. A text of any length is one row; its fragments are looked up in steps.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common, tokens


def encode(docs: DataFrame, path: str = tokens.DEFAULT) -> DataFrame:
    """doc_id, ids (little-endian uint32, packed), decoded (the text that the ids give)."""

    def run(batches):
        c = tokens.codec(path)
        for b in batches:
            ids = [c.encode(t or "") for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(ids, pa.binary()), pa.array([c.decode(x) for x in ids], pa.string())], ["doc_id", "ids", "decoded"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, ids binary, decoded string")


def encode_digests(docs: DataFrame, path: str = tokens.DEFAULT) -> DataFrame:
    """The digests of encode()'s columns, made in the worker so that ids and texts needn't return to the JVM."""

    def run(batches):
        c = tokens.codec(path)
        for b in batches:
            n, ids_sha, text_sha = [], [], []
            for t in b.column(1):
                ids = c.encode(t.as_py() or "")
                n.append(len(ids) // 4)
                ids_sha.append(hashlib.sha256(ids).hexdigest())
                text_sha.append(hashlib.sha256(c.decode(ids).encode()).hexdigest())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(np.array(n, "int64")), pa.array(ids_sha, pa.string()), pa.array(text_sha, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def op4_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_digests(common.table(spark, sf_dir, "documents"))
