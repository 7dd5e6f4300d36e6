"""Sharding by a consistent-hash ring with virtual nodes and bounded loads.

Texts hash to ring positions; a position belongs to the next virtual node clockwise.  Every shard
holds at most (1 + slack) of the mean bytes: what overflows a full shard continues clockwise to the
next virtual node whose shard has room.  Shards first take their own keys, then overflow.

The ring is never walked row by row.  Rows are ordered along the ring; the bytes of each arc (one
for each virtual node) come from an aggregation, the driver cuts the arcs into pieces - at most one
cut for each shard that fills - and a row finds its piece by the byte offset of
its middle along the ring.  Equal texts
share a position and so a shard; only a group of copies larger than `split_share` of a shard that
lies across a cut is divided.  Offsets inside a hot group are summed over salts of the doc_id.

Defined cases: a null text counts as empty (1 byte); repeated rows are rows of their own; a null
doc_id is placed like any other; an empty table gives no rows; other columns are ignored."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from innersearch.llm.common import materialize, text_or_empty

SALTS = 1024


def ring(shards: int, nodes: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted signed positions of the virtual nodes, and the shard of each."""
    import xxhash

    points = sorted((xxhash.xxh64_intdigest(f"shard {s} node {v}") - 2**63, s) for s in range(shards) for v in range(nodes))
    return np.array([p for p, _ in points], np.int64), np.array([s for _, s in points], np.int32)


def cut_arcs(loads: list[int], owner: np.ndarray, shards: int, slack: float) -> list[tuple[int, int]]:
    """Pieces (first byte offset along the ring, shard), in order, of arcs with the given bytes.

    Arc i belongs to owner[i]; the last arc, behind the last node, belongs to the first node."""
    total, n = sum(loads), len(owner)
    room = [int(-(-(total * (1 + slack)) // shards)) + 1] * shards
    pieces, over, at = [], [], 0
    for arc, load in enumerate(loads):
        s = int(owner[arc % n])
        own = min(load, room[s])
        room[s] -= own
        if own:
            pieces.append((at, s))
        if own < load:
            over.append((at + own, load - own, arc))
        at += load
    for start, left, arc in over:
        step = arc
        while left:
            step += 1
            s = int(owner[step % n])
            if not room[s]:
                continue
            took = min(left, room[s])
            pieces.append((start, s))
            room[s], start, left = room[s] - took, start + took, left - took
    pieces.sort()
    merged = [p for i, p in enumerate(pieces) if not i or pieces[i - 1][1] != p[1]]
    return merged or [(0, 0)]


def shard(docs: DataFrame, shards: int = 16, nodes: int = 128, slack: float = 0.001, split_share: float = 0.05) -> DataFrame:
    """doc_id, size, text_crc32, shard, slot for every row of docs(doc_id, text)."""
    text = text_or_empty()
    rows = materialize(
        docs.select(
            "doc_id",
            (F.octet_length(text) + 1).cast("long").alias("size"),
            F.crc32(text.cast("binary")).alias("text_crc32"),
            F.xxhash64(text).alias("at"),
            F.pmod(F.xxhash64("doc_id", F.lit("salt")), F.lit(SALTS)).cast("int").alias("salt"),
        ),
        "ring_rows",
    )
    points, owner = ring(shards, nodes)

    @F.pandas_udf("int")
    def arc_of(at: pd.Series) -> pd.Series:
        return pd.Series(np.searchsorted(points, at.to_numpy(np.int64)).astype(np.int32))

    cells = rows.groupBy("at", "salt").agg(F.sum("size").alias("bytes"), F.count("*").alias("n")).withColumn("arc", arc_of("at"))
    along = Window.partitionBy("arc").orderBy("at", "salt").rowsBetween(Window.unboundedPreceding, -1)
    cells = materialize(
        cells.select(
            F.col("arc"),
            F.col("at").alias("c_at"),
            F.col("salt").alias("c_salt"),
            "bytes",
            "n",
            F.coalesce(F.sum("bytes").over(along), F.lit(0)).alias("bytes_before"),
            F.coalesce(F.sum("n").over(along), F.lit(0)).alias("n_before"),
            F.sum("bytes").over(Window.partitionBy("arc", "at")).alias("group_bytes"),
            F.coalesce(F.min("salt").over(Window.partitionBy("arc", "at")), F.lit(0)).alias("first_salt"),
        ),
        "ring_cells",
    )
    per_arc = {r["arc"]: (r["b"], r["n"]) for r in cells.groupBy("arc").agg(F.sum("bytes").alias("b"), F.sum("n").alias("n")).collect()}
    loads = [per_arc.get(a, (0, 0))[0] for a in range(len(points) + 1)]
    counts = [per_arc.get(a, (0, 0))[1] for a in range(len(points) + 1)]
    pieces = cut_arcs(loads, owner, shards, slack)
    starts, shard_of = np.array([p[0] for p in pieces], np.int64), np.array([p[1] for p in pieces], np.int32)
    byte_base, row_base = np.concatenate([[0], np.cumsum(loads)]).astype(np.int64), np.concatenate([[0], np.cumsum(counts)]).astype(np.int64)
    whole = max(1, int(sum(loads) / shards * split_share))

    @F.pandas_udf("struct<piece:int, row:long>")
    def place(arc: pd.Series, offset: pd.Series, row: pd.Series) -> pd.DataFrame:
        a = arc.to_numpy(np.int64)
        piece = np.searchsorted(starts, byte_base[a] + offset.to_numpy(np.int64), "right") - 1
        return pd.DataFrame({"piece": piece.astype(np.int32), "row": row_base[a] + row.to_numpy(np.int64)})

    group_start = F.min("bytes_before").over(Window.partitionBy("arc", "c_at"))
    cells = cells.withColumn("group_start", group_start)
    inside = Window.partitionBy("at", "salt").orderBy("doc_id", "size", "text_crc32").rowsBetween(Window.unboundedPreceding, -1)
    placed = rows.join(cells, (F.col("at") == F.col("c_at")) & (F.col("salt") == F.col("c_salt"))).select(
        "doc_id",
        "size",
        "text_crc32",
        "arc",
        F.when(F.col("group_bytes") <= whole, F.col("group_start") + F.floor(F.col("group_bytes") / 2))
        .otherwise(F.col("bytes_before") + F.coalesce(F.sum("size").over(inside), F.lit(0)) + F.floor(F.col("size") / 2))
        .alias("offset"),
        (F.col("n_before") + F.coalesce(F.count("*").over(inside), F.lit(0))).alias("row"),
    )
    placed = materialize(placed.withColumn("p", place("arc", "offset", "row")).select("doc_id", "size", "text_crc32", "p.piece", "p.row"), "ring_placed")
    held = {r["piece"]: (r["lo"], r["n"]) for r in placed.groupBy("piece").agg(F.min("row").alias("lo"), F.count("*").alias("n")).collect()}
    slots, shift = [0] * shards, np.zeros(len(pieces), np.int64)
    for p in range(len(pieces)):
        if p in held:
            lo, n = held[p]
            shift[p] = slots[shard_of[p]] - lo
            slots[shard_of[p]] += n

    @F.pandas_udf("struct<shard:int, slot:long>")
    def finish(piece: pd.Series, row: pd.Series) -> pd.DataFrame:
        p = piece.to_numpy(np.int64)
        return pd.DataFrame({"shard": shard_of[p], "slot": row.to_numpy(np.int64) + shift[p]})

    return placed.withColumn("f", finish("piece", "row")).select("doc_id", "size", "text_crc32", "f.shard", "f.slot")


def law_digest(docs: DataFrame) -> DataFrame:
    """The shards of all docs under the law of near-equal bytes."""
    out = shard(docs)
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
