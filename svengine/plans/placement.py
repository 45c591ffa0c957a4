"""Chunks to memory spaces by priority, buffers reserved first. Distributed: a running sum over the few spaces, then a range join."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def place_chunks(spaces: DataFrame, chunks: DataFrame, chunk_bytes: int, reserve_chunks: int = 0) -> DataFrame:
    """chunk, space, tier, node. spaces: space, node, tier, capacity_bytes, priority; chunks beyond all capacity get no row."""
    if not spaces.where("capacity_bytes < 0").isEmpty():
        raise ValueError("a capacity is negative")
    room = F.greatest(F.floor(F.col("capacity_bytes") / chunk_bytes) - reserve_chunks, F.lit(0))
    upto = F.sum("room").over(Window.orderBy("priority", "space"))
    s = spaces.withColumn("room", room).withColumn("hi", upto).withColumn("lo", F.col("hi") - F.col("room"))
    return chunks.join(F.broadcast(s), (F.col("chunk") >= F.col("lo")) & (F.col("chunk") < F.col("hi"))).select("chunk", "space", "tier", "node")
