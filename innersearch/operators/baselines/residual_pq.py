"""Residual product quantization on the lossless lift: coarse cells, rotated residuals, lookup tables."""

from __future__ import annotations

import dataclasses

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from innersearch.functions import vectors as V
from innersearch.operators.exact import spread, top_k
from innersearch.operators.kmeans import hash_share

#: Most points that the codebooks are trained on.
SAMPLE_ROWS = 50_000


def _coding():
    """The steps of encoding, on a codebook's fields as a dict.  They are nested, so tasks get them by value: executors need not
    have this package."""

    def near(x, c):
        c2, out, step = (c * c).sum(1)[None], np.empty(len(x), np.int64), max(1, 2**19 // max(1, len(c)))
        for a in range(0, len(x), step):  # distances of a slice at a time, 4 MB
            out[a : a + step] = (c2 - 2 * x[a : a + step] @ c.T).argmin(1)
        return out

    def lift(book, v):
        extra = np.sqrt(np.maximum(0, book["bound2"] - (v * v).sum(1)))[:, None]
        return np.hstack([v, extra, np.zeros((len(v), book["pad"]))])

    def rotated(book, x, cell):
        out = np.empty_like(x)
        for c in np.unique(cell):
            r = x[cell == c]
            out[cell == c] = (r - book["cells"][c] if book["residual"] else r) @ book["rotations"][c]
        return out

    def encode(book, v):
        x = lift(book, v)
        cell = near(x, book["cells"])
        r = rotated(book, x, cell)
        w = r.shape[1] // len(book["books"])
        return cell, np.stack([near(r[:, i * w : (i + 1) * w], b) for i, b in enumerate(book["books"])], 1)

    return near, lift, rotated, encode


_near, _lift, _rotated, _encode = _coding()


def _kmeans(x: np.ndarray, k: int, iters: int = 8) -> np.ndarray:
    c = x[np.linspace(0, len(x) - 1, min(k, len(x))).astype(int)].copy()
    for _ in range(iters):
        near = _near(x, c)
        sums, counts = np.zeros_like(c), np.bincount(near, minlength=len(c))
        np.add.at(sums, near, x)
        c = np.where(counts[:, None] > 0, sums / np.maximum(counts, 1)[:, None], c)
    return c


@dataclasses.dataclass
class Codebook:
    bound2: float
    pad: int
    cells: np.ndarray
    rotations: np.ndarray
    books: list[np.ndarray]
    residual: bool

    @property
    def nbytes(self) -> int:
        """Bytes of cells, rotations and codebooks."""
        return self.cells.nbytes + self.rotations.nbytes + sum(b.nbytes for b in self.books)

    def lift(self, v: np.ndarray) -> np.ndarray:
        return _lift(vars(self), v)

    def rotated(self, x: np.ndarray, cell: np.ndarray) -> np.ndarray:
        return _rotated(vars(self), x, cell)

    def encode(self, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return _encode(vars(self), v)


def train(points: DataFrame, d: int, subspaces: int = 16, centroids: int = 256, cells: int = 64, rotate: bool = True, residual: bool = True) -> Codebook:
    """Codebooks from a bounded sample (all points if there are fewer), by hash order of ids."""
    n = points.count()
    some = points if n <= SAMPLE_ROWS else points.where(hash_share("vec_id") < SAMPLE_ROWS / n)
    v = some.orderBy("vec_id").select("v").toArrow()["v"].combine_chunks()
    v = v.flatten().to_numpy().reshape(len(v), -1)
    bound2 = float(points.agg(F.max(V.sq("v"))).first()[0])
    pad = -(d + 1) % subspaces
    book = Codebook(bound2, pad, np.zeros((1, d + 1 + pad)), np.eye(d + 1 + pad)[None], [], residual)
    x = book.lift(v)
    del v
    book.cells = _kmeans(x, min(cells, len(x)))
    near = _near(x, book.cells)
    book.rotations = np.stack([np.eye(x.shape[1])] * len(book.cells))
    if rotate:
        for c in range(len(book.cells)):
            r = x[near == c] - book.cells[c]
            if len(r) > 1:
                # of the triangle alone: the left factor of all rows has the square of their number
                book.rotations[c] = np.linalg.svd(np.linalg.qr(r, mode="r"), full_matrices=True)[2].T[:, _deal(x.shape[1], subspaces)]
    r = book.rotated(x, near)
    w = x.shape[1] // subspaces
    book.books = [_kmeans(r[:, i * w : (i + 1) * w], min(centroids, len(r))) for i in range(subspaces)]
    return book


def _deal(width: int, subspaces: int) -> np.ndarray:
    """Deals principal directions round the subspaces, so that each gets its share of the variance."""
    return np.argsort(np.arange(width) % subspaces, kind="stable")


def encode(points: DataFrame, book: Codebook) -> DataFrame:
    """vec_id, v, cell, codes."""
    shared, code = points.sparkSession.sparkContext.broadcast(vars(book)), _encode

    def run(batches):
        import pyarrow as pa

        for b in batches:
            if b.num_rows:
                v = b.column(1).flatten().to_numpy().reshape(b.num_rows, -1)
                cell, codes = code(shared.value, v)
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(cell.astype(np.int32)), pa.array(codes.astype(np.int32).tolist(), pa.list_(pa.int32()))], names=["vec_id", "v", "cell", "codes"])

    return points.select("vec_id", "v").mapInArrow(run, "vec_id long, v array<double>, cell int, codes array<int>")


def probed(queries: DataFrame, book: Codebook, nprobe: int = 16) -> tuple[np.ndarray, np.ndarray, dict[int, tuple[np.ndarray, np.ndarray]]]:
    """Ids and vectors of the queries, and by cell the queries that read it with their rotated residuals; a bounded batch of queries."""
    rows = queries.select("qid", "qv").toArrow()
    qids, met = rows["qid"].to_numpy(), {}
    q = rows["qv"].combine_chunks().flatten().to_numpy().reshape(len(qids), -1)
    for at, one in enumerate(q):
        x = np.concatenate([one * np.sqrt(book.bound2) / max(np.linalg.norm(one), 1e-12), np.zeros(1 + book.pad)])
        d2 = ((book.cells - x) ** 2).sum(1)
        for c in np.argsort(d2, kind="stable")[:nprobe]:
            met.setdefault(int(c), []).append((at, (x - book.cells[c] if book.residual else x) @ book.rotations[c]))
    return qids, q, {c: (np.array([i for i, _ in x]), np.array([r for _, r in x])) for c, x in met.items()}


def probes(queries: DataFrame, book: Codebook, nprobe: int = 16) -> DataFrame:
    """qid, cell of the nearest cells, one row each."""
    qids, _, met = probed(queries, book, nprobe)
    return queries.sparkSession.createDataFrame([(int(qids[i]), c) for c, (at, _) in met.items() for i in at], "qid long, cell int")


def reads(index: DataFrame, queries: DataFrame, book: Codebook, nprobe: int = 16, rerank: int = 100) -> DataFrame:
    """qid, vec_id, ip of the `rerank` least table distances in the nearest cells.

    Tables are made in the tasks from the residuals that are sent to them; a record batch passes on at most `rerank` rows a query."""
    if queries.isEmpty():
        return queries.select("qid", F.col("qid").alias("vec_id"), F.lit(0.0).alias("ip"))
    shared = queries.sparkSession.sparkContext.broadcast((*probed(queries, book, nprobe), book.books))

    def run(batches):
        import pyarrow as pa

        qids, q, met, books = shared.value
        for b in batches:
            ids, cells = b.column(0).to_numpy(), b.column(1).to_numpy()
            codes = b.column(2).flatten().to_numpy().reshape(b.num_rows, -1)
            v = b.column(3).flatten().to_numpy().reshape(b.num_rows, -1)
            parts = []
            for c in np.unique(cells):
                if int(c) not in met:
                    continue
                asked, r = met[int(c)]
                rows = np.nonzero(cells == c)[0]
                rows = rows[np.argsort(ids[rows], kind="stable")]
                w, near = r.shape[1] // len(books), np.zeros((len(asked), len(rows)))
                for i, book in enumerate(books):
                    near += ((book[None] - r[:, None, i * w : (i + 1) * w]) ** 2).sum(2)[:, codes[rows, i]]
                near[qids[asked][:, None] == ids[rows][None]] = np.inf
                # ties to the smaller id, as rows are in id order
                at = np.argsort(near, axis=1, kind="stable")[:, :rerank] if len(rows) > rerank else np.broadcast_to(np.arange(len(rows)), near.shape)
                parts.append((np.repeat(asked, at.shape[1]), rows[at].ravel(), np.take_along_axis(near, at, 1).ravel()))
            if not parts:
                continue
            qi, row, near = (np.concatenate(x) for x in zip(*parts, strict=True))
            qi, row, near = (x[np.isfinite(near)] for x in (qi, row, near))
            order = np.lexsort((ids[row], near, qi))
            qi, row, near = qi[order], row[order], near[order]
            keep = np.arange(len(qi)) - np.searchsorted(qi, qi) < rerank
            qi, row, near = qi[keep], row[keep], near[keep]
            ip = np.zeros(len(qi))
            for a, x in zip(v.T, q.T, strict=True):  # summed in order, as vector expressions do
                ip += a[row] * x[qi]
            yield pa.RecordBatch.from_arrays([pa.array(qids[qi]), pa.array(ids[row]), pa.array(-near), pa.array(ip)], names=["qid", "vec_id", "near", "ip"])

    met = spread(index.select("vec_id", "cell", "codes", "v")).mapInArrow(run, "qid long, vec_id long, near double, ip double")
    return top_k(met, rerank, "near", keep=("ip",)).select("qid", "vec_id", "ip")


def search(index: DataFrame, queries: DataFrame, book: Codebook, k: int = 10, nprobe: int = 16, rerank: int = 100) -> DataFrame:
    """hits after re-ranking the points read by the true product."""
    return top_k(reads(index, queries, book, nprobe, rerank), k)


def code_pages(index: DataFrame, queries: DataFrame, book: Codebook, page: int, nprobe: int = 16) -> DataFrame:
    """qid, index_pages: pages of ids and codes in the inverted lists of the nearest cells, each list from a page of its own."""
    entry = 8 + len(book.books)
    lists = index.groupBy("cell").agg(F.ceil(F.count("*") * entry / page).alias("pages"))
    return probes(queries, book, nprobe).select("qid", "cell").join(F.broadcast(lists), "cell").groupBy("qid").agg(F.sum("pages").cast("long").alias("index_pages"))
