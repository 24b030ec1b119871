"""Approximate nearest neighbours: an inverted file of coarse centroids with product-quantised residuals.

Fitted on a bounded sample of vectors (`sample_rows`): k-means gives the coarse lists, k-means on each part of the
residuals gives the codebooks. Every vector is then indexed. The number of lists that a query probes is the least that
reaches `reach` of the true neighbours of at most MEASURED queries, which one pass finds among all rows by brute force.
A query meets the cells of its lists: distances to the codes come from its table of distances to the codewords
(asymmetric), and the best `rerank` of each cell are measured exactly on the original vectors. A row is no further from
its code than its coding error, so every other row that this bound leaves below the k-th of them is measured too: codes
too coarse for a tight group, or for the small ones of vectors of many scales, cost time and lose nothing. The nearest of
all cells win.

A cell is a salted part of a list of about CELL_ROWS vectors met by a block of at most QUERY_ROWS queries, so a list
that holds a third of all vectors, or that all queries probe, is spread over many tasks.

Defined cases: null and zero vectors, vectors holding null or non-finite components, and vectors of another length than
most take no part; a null vec_id takes no part; repeated vectors are ordered by id, and rows of one vec_id are
one candidate each; with fewer candidates than k, all found; an empty table gives no rows; other columns are ignored."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import window as W

from . import common

CELL_ROWS, QUERY_ROWS, MOST_LISTS = 8192, 512, 4096
#: Queries whose true neighbours are found by brute force, for the number of lists to probe.
MEASURED = 256


def usable(vectors: DataFrame) -> DataFrame:
    """vec_id, v of the rows that take part."""
    rows = vectors.where("vec_id is not null and embedding is not null").select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("v"))
    odd = F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return rows.where(~odd & F.exists("v", lambda x: x != 0))


def kmeans(x: np.ndarray, k: int, rounds: int, rng: np.random.Generator) -> np.ndarray:
    c = x[rng.choice(len(x), min(k, len(x)), replace=False)].copy()
    for _ in range(rounds):
        near = nearest(x, c)
        n = np.bincount(near, minlength=len(c))
        sums = np.stack([np.bincount(near, x[:, j], len(c)) for j in range(x.shape[1])], axis=1)
        c[n > 0] = sums[n > 0] / n[n > 0, None]
        if (empty := np.flatnonzero(n == 0)).size:
            c[empty] = x[rng.choice(len(x), len(empty))]
    return c


def squares(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return (c * c).sum(axis=1)[None, :] - 2 * x @ c.T  # without |x|^2, which is the same for all c


def nearest(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return np.concatenate([squares(x[at : at + 4096], c).argmin(axis=1) for at in range(0, len(x), 4096)]) if len(x) else np.zeros(0, np.int64)


@dataclass
class Index:
    dim: int
    coarse: np.ndarray  # (lists, dim)
    books: np.ndarray  # (parts, codewords, width)
    probes: int

    def split(self, r: np.ndarray) -> np.ndarray:
        parts, _, width = self.books.shape
        padded = np.zeros((len(r), parts * width))
        padded[:, : self.dim] = r
        return padded.reshape(len(r), parts, width)

    def encode(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        at = nearest(x, self.coarse)
        r = self.split(x - self.coarse[at])
        return at, np.stack([nearest(r[:, p], self.books[p]) for p in range(len(self.books))], axis=1).astype(np.uint8)

    def decode(self, at: int, codes: np.ndarray) -> np.ndarray:
        """What the codes of one list stand for."""
        parts = self.books[np.arange(len(self.books))[None, :], codes]
        return self.coarse[at] + parts.reshape(len(codes), -1)[:, : self.dim]

    def probed(self, q: np.ndarray) -> np.ndarray:
        return np.argsort(squares(q, self.coarse), axis=1, kind="stable")[:, : self.probes]

    def tables(self, q: np.ndarray, list_id: int) -> np.ndarray:
        """(queries, parts, codewords): squared distances of the queries' residuals to the codewords."""
        r = self.split(q - self.coarse[list_id])
        return ((r[:, :, None, :] - self.books[None]) ** 2).sum(axis=3)


def train(rows: DataFrame, sample_rows: int = 16_000, parts: int = 16, seed: int = 5) -> Index | None:
    """From the rows with the smallest hashes of their ids. The number of lists follows the number of rows; all are probed until `depth` is told."""
    n = rows.count()
    picked = rows.orderBy(F.xxhash64("vec_id"), "vec_id").limit(sample_rows).toArrow().sort_by("vec_id")["v"].to_pylist()
    if not picked:
        return None
    sizes = np.array([len(v) for v in picked])
    dim = int(np.bincount(sizes).argmax())
    x = np.array([v for v in picked if len(v) == dim], dtype=np.float64)
    rng = np.random.default_rng(seed)
    lists = int(min(MOST_LISTS, max(1, round(n**0.5 / 2)), max(1, len(x) // 8)))
    coarse = kmeans(x, lists, 10, rng)
    parts = min(parts, dim)
    width = -(-dim // parts)
    index = Index(dim, coarse, np.zeros((parts, 1, width)), len(coarse))
    r = index.split(x - coarse[nearest(x, coarse)])
    index.books = np.stack([_filled(kmeans(r[:, p], 256, 6, rng), 256) for p in range(parts)])
    return index


def _filled(c: np.ndarray, k: int) -> np.ndarray:
    return np.concatenate([c, np.repeat(c[:1], k - len(c), axis=0)]) if len(c) < k else c


def _matrix(column: pa.ChunkedArray | pa.Array) -> np.ndarray:
    """Rows of equal length as one array."""
    a = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    flat = a.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(a), -1) if len(a) else np.zeros((0, 1))


def indexed(rows: DataFrame, index: Index) -> DataFrame:
    """vec_id, list, codes, v for every row."""

    def run(batches):
        for b in common.slices(batches, 4096):
            at, codes = index.encode(_matrix(b.column(1)))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(at.astype(np.int32)), pa.array([c.tobytes() for c in codes], pa.binary()), b.column(1)], ["vec_id", "list", "codes", "v"])

    return rows.where(F.size("v") == index.dim).mapInArrow(run, "vec_id long, list int, codes binary, v array<double>")


def depth(base: DataFrame, queries: DataFrame, index: Index, k: int, reach: float = 0.985) -> int:
    """How many lists to probe: the least that hold `reach` of the k nearest rows of at most MEASURED queries among all of `base`."""
    picked = queries.where(F.size("v") == index.dim).orderBy(F.xxhash64("vec_id"), "vec_id").limit(MEASURED).select("vec_id", "v").toArrow()
    if not picked.num_rows:
        return 1
    ids, q = picked["vec_id"].to_numpy(), _matrix(picked["v"])

    def run(batches):
        """The k nearest rows of a partition for each query."""
        best = None
        for b in common.slices(batches, 4096):
            d = squares(q - q[0], _matrix(b.column(3)) - q[0])
            own, at = b.column(0).to_numpy(), np.broadcast_to(b.column(1).to_numpy(), d.shape)
            d = np.where(ids[:, None] == own[None, :], np.inf, d)
            d, at = (d, at) if best is None else (np.concatenate([best[0], d], axis=1), np.concatenate([best[1], at], axis=1))
            if d.shape[1] > k:
                first = np.argpartition(d, k - 1, axis=1)[:, :k]
                d, at = np.take_along_axis(d, first, axis=1), np.take_along_axis(at, first, axis=1)
            best = d, at
        if best is not None:
            place = np.repeat(np.arange(len(q)), best[0].shape[1])
            yield pa.RecordBatch.from_arrays([pa.array(place), pa.array(best[1].ravel(), pa.int32()), pa.array(best[0].ravel())], ["place", "list", "d"])

    found = base.mapInArrow(run, "place long, list int, d double").where(F.col("d") < float("inf"))
    order = W.Window.partitionBy("place").orderBy("d")
    true = found.withColumn("r", F.row_number().over(order)).where(F.col("r") <= k).select("place", "list").toArrow()
    if not true.num_rows:
        return 1
    lists = np.argsort(np.argsort(squares(q, index.coarse), axis=1, kind="stable"), axis=1)
    down = np.sort(lists[true["place"].to_numpy(), true["list"].to_numpy()])
    return int(1 + down[min(len(down) - 1, int(np.ceil(reach * len(down))))])


def probing(queries: DataFrame, index: Index) -> DataFrame:
    """query_id, list, q: a row for each list that a query probes."""

    def run(batches):
        for b in common.slices(batches, 1024):
            lists = index.probed(_matrix(b.column(1)))
            row = pa.array(np.repeat(np.arange(b.num_rows), lists.shape[1]))
            yield pa.RecordBatch.from_arrays([b.column(0).take(row), pa.array(lists.ravel().astype(np.int32)), b.column(1).take(row)], ["query_id", "list", "q"])

    return queries.where(F.size("v") == index.dim).select("vec_id", "v").mapInArrow(run, "query_id long, list int, q array<double>")


def _spread(df: DataFrame, key: str, counts: dict[int, int], rows: int, name: str):
    """The number of parts of each list, and the part of a row."""
    many = {i: -(-n // rows) for i, n in counts.items() if n > rows}
    parts = F.lit(1) if not many else F.coalesce(F.create_map(*[F.lit(x).cast("int") for kv in many.items() for x in kv])[F.col("list")], F.lit(1))
    return df.withColumn(name, F.pmod(F.xxhash64(F.lit(name), key), parts).cast("int")), parts


def search(vectors: DataFrame, is_query, k: int = 10, sample_rows: int = 16_000, rerank: int = 160, index: Index | None = None) -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest found for each row where `is_query` holds, all rows searched."""
    schema = "query_id long, vec_id long, score double"
    rows = usable(vectors)
    index = index or train(rows, sample_rows)
    if index is None:
        return vectors.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    base = common.stored(indexed(rows, index), "index")
    index.probes = depth(base, rows.where(is_query), index, k)
    asked = common.stored(probing(rows.where(is_query), index), "queries")
    held = {r["list"]: r["n"] for r in base.groupBy("list").agg(F.count(F.lit(1)).alias("n")).collect()}  # at most MOST_LISTS rows
    met = {r["list"]: r["n"] for r in asked.groupBy("list").agg(F.count(F.lit(1)).alias("n")).collect()}
    base, salts = _spread(base, "vec_id", held, CELL_ROWS, "salt")
    asked, blocks = _spread(asked, "query_id", met, QUERY_ROWS, "block")
    base = base.withColumn("block", F.explode(F.sequence(F.lit(0), (blocks - 1).cast("int"))))
    asked = asked.withColumn("salt", F.explode(F.sequence(F.lit(0), (salts - 1).cast("int"))))

    def cell(left: pa.Table, right: pa.Table) -> pa.Table:
        out_q, out_v, out_d = [], [], []
        if left.num_rows and right.num_rows:
            left = left.sort_by("vec_id")
            ids, x = left["vec_id"].to_numpy(), _matrix(left["v"])
            codes = np.frombuffer(b"".join(left["codes"].to_pylist()), dtype=np.uint8).reshape(len(ids), -1)
            qs, qids, place = _matrix(right["q"]), right["query_id"].to_numpy(), int(left["list"][0].as_py())
            far = x - index.decode(place, codes)
            wrong = np.sqrt((far * far).sum(axis=1))  # of the codes
            near, own = x - index.coarse[place], qs - index.coarse[place]
            sizes, most = (near * near).sum(axis=1), (own * own).sum(axis=1)
            flat = codes.astype(np.int64) + np.arange(codes.shape[1]) * 256
            for at in range(0, len(qs), 64):
                table = index.tables(qs[at : at + 64], place).reshape(len(qs[at : at + 64]), -1)
                rough = sizes - 2 * own[at : at + 64] @ near.T + most[at : at + 64, None]  # squared distances, up to rounding
                for q, qid, t, squared, big in zip(qs[at : at + 64], qids[at : at + 64], table, rough, most[at : at + 64], strict=True):
                    about = t[flat].sum(axis=1)
                    best = np.arange(len(ids))
                    if len(ids) > rerank + 1:  # ties at the border go to the smaller ids, which come first
                        border = np.partition(about, rerank)[rerank]
                        under, level = np.flatnonzero(about < border), np.flatnonzero(about == border)
                        best = np.concatenate([under, level[: rerank + 1 - len(under)]])
                        d = np.sqrt(((x[best] - q) ** 2).sum(axis=1))
                        last = np.partition(d, min(k, len(d) - 1))[min(k, len(d) - 1)]  # one more than k, for the query's own row
                        bound = last + 1e-7 * (last + big**0.5)
                        open_ = (np.sqrt(about) - wrong <= bound + 1e-7 * wrong) & (squared <= bound * bound + 1e-9 * (sizes + big))
                        best = np.union1d(best, np.flatnonzero(open_))
                    best = best[ids[best] != qid]
                    d = np.sqrt(((x[best] - q) ** 2).sum(axis=1))
                    first = np.lexsort((ids[best], d))[:k]
                    out_q += [qid] * len(first)
                    out_v += ids[best][first].tolist()
                    out_d += d[first].tolist()
        return pa.table({"query_id": pa.array(out_q, pa.int64()), "vec_id": pa.array(out_v, pa.int64()), "score": pa.array(out_d, pa.float64())})

    key = ["list", "salt", "block"]
    near = base.groupBy(*key).cogroup(asked.groupBy(*key)).applyInArrow(cell, schema)
    order = W.Window.partitionBy("query_id").orderBy("score", "vec_id")
    return near.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
