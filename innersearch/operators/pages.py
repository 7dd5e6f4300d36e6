"""The page model: rows in a layout order fill pages of a fixed size; a search touches distinct pages."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from innersearch.operators.exact import ranked
from innersearch.sources import scratch

PAGE_BYTES = 4096


def row_bytes(d: int) -> int:
    return 8 + 8 * d


def touched(cells: DataFrame, subcells: DataFrame, bytes_: int, page: int = PAGE_BYTES) -> DataFrame:
    """qid, page_id of the pages that hold the touched sub-cells (neighbouring cells may share one)."""
    c = cells.join(F.broadcast(subcells), ["part", "ikey", "sub"])
    first = F.floor(F.col("row_offset") * bytes_ / page).cast("long")
    last = F.floor(((F.col("row_offset") + F.col("cnt")) * bytes_ - 1) / page).cast("long")
    return c.select("qid", F.explode(F.sequence(first, last)).alias("page_id"))


def page_access(cells: DataFrame, subcells: DataFrame, bytes_: int, page: int = PAGE_BYTES) -> DataFrame:
    """qid, pages: distinct data pages."""
    return touched(cells, subcells, bytes_, page).groupBy("qid").agg(F.count_distinct("page_id").alias("pages"))


def index_pages(cells: DataFrame, subcells: DataFrame, m: int, page: int = PAGE_BYTES) -> DataFrame:
    """qid, index_pages: pages of the sub-cell table (keys, pivot, radius, count, offset; in key order) that hold a touched one."""
    place = F.row_number().over(Window.orderBy("ikey", "sub")) - 1
    at = subcells.select("part", "ikey", "sub", F.floor(place * (8 * (m + 6)) / page).alias("leaf"))
    return cells.join(F.broadcast(at), ["part", "ikey", "sub"]).groupBy("qid").agg(F.count_distinct("leaf").alias("index_pages"))


def data_pages(read: DataFrame, placed: DataFrame) -> DataFrame:
    """qid, pages: distinct pages of the points read, read(qid, vec_id), in a layout(vec_id, page_id)."""
    return placed.join(scratch.small_side(read.select("qid", "vec_id")), "vec_id").groupBy("qid").agg(F.count_distinct("page_id").alias("pages"))


def layout(points: DataFrame, order: list, bytes_: int, page: int = PAGE_BYTES) -> DataFrame:
    """vec_id, page_id of rows laid out in an order (baselines have their own)."""
    names = [c for c in points.columns if c not in ("v", "pv")]
    placed, _ = ranked(points.select(*names), order)
    return placed.select("vec_id", F.floor(F.col("place") * bytes_ / page).cast("long").alias("page_id"))


def index_bytes(rows: int, d: int, m: int) -> dict[str, int]:
    """Logical bytes of the narrow and the wide table."""
    return {"narrow": rows * (8 + 8 * m + 8 * 4), "wide": rows * row_bytes(d)}
