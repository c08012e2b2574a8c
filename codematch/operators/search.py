"""Inverted cells, multi-sequence visits, and ranked search by cell weight and hits.

Visited cells of all queries are one relation; candidates are an equi-join of it with the
codes by cell. The relation is broadcast only while its counted size is small; otherwise
both sides are dealt by cell. Codes that are stored in the order of cells are read once.
"""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from codematch.operators import score
from codematch.operators.encode import encode_probes, fine_column, matrix, usable
from codematch.operators.model import CodeModel, slices

BROADCAST_ROWS = 500_000


def small(df: DataFrame, limit: int = BROADCAST_ROWS) -> DataFrame:
    """Broadcast up to a counted size; beyond it the join is left to shuffle."""
    return F.broadcast(df) if df.limit(limit + 1).count() <= limit else df


def cell_sizes(codes: DataFrame) -> DataFrame:
    return codes.groupBy("c1", "c2").agg(F.count(F.lit(1)).alias("n"))


def store_cells(codes: DataFrame, path: str, partitions: int | None = None) -> None:
    """Codes in the order of cells, so files and row groups hold few cells each and are skipped by min and max."""
    n = partitions or int(codes.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    codes.repartitionByRange(n, "c1", "c2").sortWithinPartitions("c1", "c2", "id").write.mode("overwrite").parquet(path)


class CellSizes:
    """Numbers of vectors of non-empty cells as two sorted arrays: 12 bytes a cell, K * K cells at most."""

    def __init__(self, cells: np.ndarray, n: np.ndarray, K: int):
        order = np.argsort(cells)
        self.cells, self.n, self.K = cells[order], n[order].astype(np.int32 if not len(n) or n.max() < 1 << 31 else np.int64), K

    @classmethod
    def of(cls, sizes: DataFrame, K: int) -> CellSizes:
        rows = sizes.select((F.coalesce("c1", F.lit(0)).cast("long") * K + F.coalesce("c2", F.lit(0))).alias("cell"), "n").toArrow()
        return cls(rows.column("cell").to_numpy(), rows.column("n").to_numpy(), K)

    def get(self, cell: tuple[int, int], default: int = 0) -> int:
        key = cell[0] * self.K + cell[1]
        at = int(np.searchsorted(self.cells, key))
        return int(self.n[at]) if at < len(self.cells) and self.cells[at] == key else default


def visit(half_distances: list[np.ndarray], sizes: CellSizes, quota: int) -> list[tuple[int, int, float, int]]:
    """Non-empty cells by rising d1 + d2, ties by (c1, c2), until `quota` vectors are seen: (c1, c2, d, n).

    With a single coarse space cells are its clusters, by distance; c2 is 0 then.
    """
    one, two = half_distances if len(half_distances) == 2 else (half_distances[0], np.zeros(1))
    o1, o2 = np.lexsort((np.arange(len(one)), one)), np.lexsort((np.arange(len(two)), two))
    heap, pushed, out, seen = [(one[o1[0]] + two[o2[0]], int(o1[0]), int(o2[0]), 0, 0)], {(0, 0)}, [], 0
    while heap and seen < quota:
        d, c1, c2, i, j = heapq.heappop(heap)
        n = sizes.get((c1, c2), 0)
        if n:
            out.append((c1, c2, float(d), n))
            seen += n
        for a, b in ((i + 1, j), (i, j + 1)):
            if a < len(o1) and b < len(o2) and (a, b) not in pushed:
                pushed.add((a, b))
                heapq.heappush(heap, (one[o1[a]] + two[o2[b]], int(o1[a]), int(o2[b]), a, b))
    return out


VISITED = "qid long, ord int, c1 int, c2 int, d double, n long, seen long"
_CELL = (pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.float64(), pa.int64(), pa.int64())
#: Queries whose distances to all clusters are held at once.
QUERIES = 256


def visited_cells(queries: DataFrame, model: CodeModel, sizes: DataFrame, quota: int, codes: bool = False) -> DataFrame:
    """(qid, ord, c1, c2, d, n, seen) for each query; the list that brings the count to the quota is the last, and counts whole.

    codes adds qfine, the query's fine codes relative to each cell's clusters: only clusters
    that it visits are encoded, in this same pass. c2 is null with a single coarse space. The
    sizes of the non-empty cells are broadcast: K * K numbers at most, not more with more data.
    """
    spark = queries.sparkSession
    table, sent = spark.sparkContext.broadcast(CellSizes.of(sizes, model.K)), spark.sparkContext.broadcast(model)

    def own_codes(model: CodeModel, x: np.ndarray, rows: list[tuple], at: list[int]) -> np.ndarray:
        """(cells, m): codes of the query of each cell, each (query, cluster) pair encoded once."""
        out = []
        for h in range(model.halves):
            pairs, back = np.unique(np.array([(i, r[2 + h]) for i, r in zip(at, rows, strict=True)]), axis=0, return_inverse=True)
            step = slices(len(pairs), model.dh * model.dh).step
            fine = [model.fine(x[pairs[j : j + step, 0]], h, pairs[j : j + step, 1]) for j in range(0, len(pairs), step)]
            out.append(np.concatenate(fine)[back.ravel()])
        return np.concatenate(out, 1)

    def run(batches):
        model = sent.value
        for batch in batches:
            for lo in range(0, batch.num_rows, QUERIES):
                part = batch.slice(lo, QUERIES)
                x = model.prepare(matrix(part, 1, model.raw))
                rows, at = [], []
                for i, (q, *dist) in enumerate(zip(part.column(0).to_pylist(), *model.half_distances(x), strict=True)):
                    seen = 0
                    for k, (c1, c2, d, n) in enumerate(visit(dist, table.value, quota), 1):
                        seen += n
                        rows.append((q, k, c1, c2, d, n, seen))
                        at.append(i)
                if rows:
                    cols = [pa.array(c, t) for c, t in zip(zip(*rows, strict=True), _CELL, strict=True)]
                    if model.halves == 1:
                        cols[3] = pa.nulls(len(rows), pa.int32())
                    names = ["qid", "ord", "c1", "c2", "d", "n", "seen"]
                    if codes:
                        cols, names = [*cols, fine_column(own_codes(model, x, rows, at))], [*names, "qfine"]
                    yield pa.RecordBatch.from_arrays(cols, names=names)

    return usable(queries).mapInArrow(run, VISITED + (", qfine array<smallint>" if codes else ""))


def same_cell(cells: DataFrame, codes: DataFrame, model: CodeModel) -> DataFrame:
    """Equi-join by cell; by cluster with a single coarse space."""
    if model.halves == 2:
        return cells.join(codes, ["c1", "c2"])
    return cells.drop("c2").join(codes, "c1")


def visited_cells_relational(queries: DataFrame, model: CodeModel, sizes: DataFrame, quota: int, max_cells: int = 64) -> DataFrame:
    """The same by joins and windows: of ranks (r1, r2) only r1 * r2 <= max_cells can be among the first max_cells cells, so the cut loses nothing.

    Where the quota is not met within the cut, max_cells doubles.
    """
    k = model.K
    near = encode_probes(queries, model, k).select("id", "half", "rnk", "c", "d")
    pairs = near.where("half = 0").select(F.col("id").alias("qid"), F.col("rnk").alias("r1"), F.col("c").alias("c1"), F.col("d").alias("d1"))
    other = near.where("half = 1").select(F.col("id").alias("qid"), F.col("rnk").alias("r2"), F.col("c").alias("c2"), F.col("d").alias("d2"))
    need = queries.count()
    while True:
        w = Window.partitionBy("qid").orderBy("d", "c1", "c2")
        ranked = pairs.join(other, "qid").where(F.col("r1") * F.col("r2") <= max_cells).select("qid", "c1", "c2", (F.col("d1") + F.col("d2")).alias("d")).withColumn("cell", F.row_number().over(w)).where(F.col("cell") <= max_cells)
        seen = ranked.join(sizes, ["c1", "c2"]).withColumn("seen", F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, 0)))
        if max_cells >= k * k or seen.groupBy("qid").agg(F.max("seen").alias("s")).where(F.col("s") >= quota).count() == need:
            break
        max_cells *= 2
    return seen.where(F.col("seen") - F.col("n") < quota).withColumn("ord", F.row_number().over(w)).select("qid", F.col("ord").cast("int").alias("ord"), "c1", "c2", "d", "n", "seen")


def candidates(visited: DataFrame, codes: DataFrame, exclude_self: bool = True) -> DataFrame:
    """(qid, id, ...) for every vector of the visited cells."""
    out = small(visited.select("qid", "ord", "c1", "c2", "d")).join(codes, ["c1", "c2"])
    return out.where("qid <> id") if exclude_self else out


def knn(queries: DataFrame, model: CodeModel, codes: DataFrame, R: int, T: int, weight: str = "exp", scale: float = 1.0, exclude_self: bool = True, sizes: DataFrame | None = None) -> DataFrame:
    """(qid, id, score, rnk): the R best of the T nearest candidates by cell weight plus hits; ties by id.

    A query's fine codes are taken relative to each cell's clusters.
    """
    cells = visited_cells(queries, model, sizes if sizes is not None else cell_sizes(codes), T, codes=True)
    met = same_cell(small(cells.select("qid", "c1", "c2", "d", "qfine")), codes, model)
    if exclude_self:
        met = met.where("qid <> id")
    s = score.weighted(F.col("d"), score.hits(F.col("qfine"), F.col("fine"), model.m), weight, scale)
    return top(met.select("qid", "id", s.cast("double").alias("score")), R)


def top(scored: DataFrame, R: int, key: str = "qid", rising: bool = False) -> DataFrame:
    """The R best of each query, ties by id; the window's limit is applied before the shuffle."""
    w = Window.partitionBy(key).orderBy(F.col("score").asc() if rising else F.col("score").desc(), "id")
    return scored.withColumn("rnk", F.row_number().over(w)).where(F.col("rnk") <= R)
