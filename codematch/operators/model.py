"""The code model: coarse clusters, rotations and sub-codebooks, and encoding in numpy.

A model is small, lives on the driver and is sent to tasks by closure or broadcast; its size
does not follow the data. Sums run over dimensions in order and ties go to the smallest
index, so any engine that adds in this order finds the same codes.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


#: Distances computed at once: an Arrow batch against many centroids goes in slices of rows.
CELLS = 1 << 21


def slices(n: int, k: int) -> range:
    """Starts of slices of n rows that have CELLS distances to k centroids or less (one row at least)."""
    return range(0, n, max(1, CELLS // max(k, 1)))


def squared(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Squared distances of the rows of x and c, summed in the order of dimensions."""
    out = np.zeros((len(x), len(c)))
    step = slices(len(x), len(c)).step
    for at in slices(len(x), len(c)):
        part = out[at : at + step]
        for i in range(x.shape[1]):
            diff = x[at : at + step, i, None] - c[:, i]
            diff *= diff
            part += diff
    return out


def nearest(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Index of the nearest row of c, the smallest on ties."""
    step = slices(len(x), len(c)).step
    return np.concatenate([squared(x[at : at + step], c).argmin(1) for at in slices(len(x), len(c))] or [np.empty(0, np.int64)])


@dataclass
class CodeModel:
    """halves: 1 or 2 coarse spaces; coarse[h][K][d/halves]; rot[h][K] square or None; sub[m][k][d/m], or
    sub[h][K][m/halves][k][d/m] with local codebooks. mean, pca and perm prepare raw vectors."""

    m: int
    coarse: np.ndarray
    sub: np.ndarray
    rot: np.ndarray | None = None
    mean: np.ndarray | None = None
    pca: np.ndarray | None = None
    perm: np.ndarray | None = None
    version: str = "1"
    trained_on: str = ""
    extra: dict = field(default_factory=dict)

    def __post_init__(self):
        self.coarse, self.sub = np.asarray(self.coarse, float), np.asarray(self.sub, float)
        self.halves, self.K, self.dh = self.coarse.shape
        self.d = self.halves * self.dh
        if self.m % self.halves or self.d % self.m:
            raise ValueError("each half needs m / halves blocks of d / m dimensions")
        #: Dimensions of vectors before preparation.
        self.raw = len(self.mean) if self.mean is not None else self.pca.shape[0] if self.pca is not None else self.d
        self.local = self.sub.ndim == 5
        self.k = self.sub.shape[-2]
        if self.sub.shape[-1] != self.d // self.m:
            raise ValueError("sub-centroids need d / m dimensions")
        if self.k > 32767:
            raise ValueError("fine codes have 16 bits")
        for a in (self.coarse, self.sub, self.rot, self.mean, self.pca):
            if a is not None and not np.isfinite(a).all():
                raise ValueError("a model holds finite numbers only")
        if self.rot is not None and np.abs(np.einsum("hkij,hkil->hkjl", self.rot, self.rot) - np.eye(self.dh)).max() > 1e-6:
            raise ValueError("rotations are orthogonal")

    def prepare(self, x: np.ndarray) -> np.ndarray:
        x = np.asarray(x, float)
        if self.mean is not None:
            x = x - self.mean
        if self.pca is not None:
            x = x @ self.pca
        return x[:, self.perm] if self.perm is not None else x

    def nearest_clusters(self, x: np.ndarray) -> np.ndarray:
        """(n, halves): the nearest cluster of each half, of prepared vectors."""
        return np.stack([nearest(x[:, h * self.dh : (h + 1) * self.dh], self.coarse[h]) for h in range(self.halves)], 1)

    def half_distances(self, x: np.ndarray) -> list[np.ndarray]:
        """Squared distances to the centroids of each half, of prepared vectors."""
        return [squared(x[:, h * self.dh : (h + 1) * self.dh], self.coarse[h]) for h in range(self.halves)]

    def residual(self, x: np.ndarray, h: int, c: np.ndarray) -> np.ndarray:
        """Rotated residuals of prepared vectors in half h relative to centroids c."""
        r = x[:, h * self.dh : (h + 1) * self.dh] - self.coarse[h][c]
        if self.rot is None:
            return r
        out = np.empty_like(r)
        for i in np.unique(c):
            own = np.flatnonzero(c == i)
            out[own] = r[own] @ self.rot[h][i].T
        return out

    def books(self, h: int, b: int, c: np.ndarray):
        """The codebook of block b of half h: one for all, or one for each vector's cluster."""
        return self.sub[h][:, b][c] if self.local else self.sub[h * (self.m // self.halves) + b]

    def fine(self, x: np.ndarray, h: int, c: np.ndarray) -> np.ndarray:
        """Fine codes of half h relative to centroids c: (n, m / halves)."""
        r, w = self.residual(x, h, c), self.d // self.m
        out = []
        for b in range(self.m // self.halves):
            part, book = r[:, b * w : (b + 1) * w], self.books(h, b, c)
            if self.local:
                dist = np.zeros((len(x), self.k))
                for i in range(w):
                    dist += (part[:, i, None] - book[:, :, i]) ** 2
                out.append(dist.argmin(1))
            else:
                out.append(nearest(part, book))
        return np.stack(out, 1) if out else np.empty((len(x), 0), int)

    def encode(self, raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(coarse codes (n, halves), fine codes (n, m)) of raw vectors."""
        x = self.prepare(raw)
        c = self.nearest_clusters(x)
        return c, np.concatenate([self.fine(x, h, c[:, h]) for h in range(self.halves)], 1)

    def decode(self, c: np.ndarray, f: np.ndarray) -> np.ndarray:
        """Prepared-space reconstructions."""
        out, per = [], self.m // self.halves
        for h in range(self.halves):
            r = np.concatenate([self.sub[h][c[:, h], b, f[:, h * per + b]] if self.local else self.sub[h * per + b][f[:, h * per + b]] for b in range(per)], 1)
            out.append(self.coarse[h][c[:, h]] + (r if self.rot is None else np.einsum("nji,nj->ni", self.rot[h][c[:, h]], r)))
        return np.concatenate(out, 1)

    # ---- as a table

    def rows(self) -> list[tuple]:
        out = [("shape", 0, 0, 0, 0, [float(self.m), float(self.halves), float(self.K), float(self.k), float(self.local)])]
        out += [("coarse", h, c, 0, 0, v.tolist()) for h, x in enumerate(self.coarse) for c, v in enumerate(x)]
        if self.rot is not None:
            out += [("rotation", h, c, 0, i, v.tolist()) for h, x in enumerate(self.rot) for c, r in enumerate(x) for i, v in enumerate(r)]
        if self.local:
            out += [("sub", h, c, b, j, v.tolist()) for h, x in enumerate(self.sub) for c, y in enumerate(x) for b, z in enumerate(y) for j, v in enumerate(z)]
        else:
            out += [("sub", 0, 0, b, j, v.tolist()) for b, z in enumerate(self.sub) for j, v in enumerate(z)]
        if self.mean is not None:
            out.append(("mean", 0, 0, 0, 0, self.mean.tolist()))
        if self.pca is not None:
            out += [("pca", 0, 0, 0, i, v.tolist()) for i, v in enumerate(self.pca)]
        if self.perm is not None:
            out.append(("permutation", 0, 0, 0, 0, [float(i) for i in self.perm]))
        return out

    def save(self, spark: SparkSession, path: str) -> None:
        spark.createDataFrame(self.rows(), MODEL_ROWS).coalesce(1).write.mode("overwrite").parquet(path)

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> CodeModel:
        by: dict[str, list] = {}
        for r in sorted(spark.read.parquet(path).collect(), key=lambda r: r[:5]):
            by.setdefault(r.kind, []).append(r)
        m, halves, K, k, local = (int(x) for x in by["shape"][0].vec)
        grid = lambda kind, *shape: np.array([r.vec for r in by[kind]]).reshape(*shape, -1)
        dh = len(by["coarse"][0].vec)
        one = lambda kind: np.array(by[kind][0].vec) if kind in by else None
        perm = one("permutation")
        return cls(m=m, coarse=grid("coarse", halves, K), sub=grid("sub", halves, K, m // halves, k) if local else grid("sub", m, k), rot=grid("rotation", halves, K, dh) if "rotation" in by else None, mean=one("mean"), pca=grid("pca", len(by["pca"])) if "pca" in by else None, perm=perm.astype(int) if perm is not None else None)


MODEL_ROWS = "kind string, half int, cluster int, block int, idx int, vec array<double>"


def signed_permutation(d: int) -> np.ndarray:
    """A fixed rotation for tests: dimension i takes dimension (3 i + 1) mod d (5 i + 1 if 3 divides d), with signs in turn."""
    step = 3 if d % 3 else 5
    r = np.zeros((d, d))
    for i in range(d):
        r[i, (step * i + 1) % d] = 1.0 if i % 2 == 0 else -1.0
    return r


def anchor(df: DataFrame, K: int, m: int, k: int, halves: int = 2, local: bool = False, rotate: bool = False) -> CodeModel:
    """A model without training: the first K rows by id are coarse centroids; the residuals of the next k
    rows are sub-centroids. With local codebooks those of a cluster are the residuals of its first k members by id."""
    rows = sorted((r.id, r.vec) for r in df.where("vec IS NOT NULL").select("id", "vec").orderBy("id").limit(K + k).collect())
    x = np.array([v for _, v in rows], float)
    if len(x) < K + k:
        raise ValueError(f"{K + k} rows are needed, {len(x)} are there")
    d = x.shape[1]
    dh = d // halves
    coarse = np.stack([x[:K, h * dh : (h + 1) * dh] for h in range(halves)])
    rot = np.broadcast_to(signed_permutation(dh), (halves, K, dh, dh)).copy() if rotate else None
    model = CodeModel(m=m, coarse=coarse, sub=np.zeros((m, k, d // m)), rot=rot)
    if not local:
        s = x[K:]
        c = [z.argmin(1) for z in model.half_distances(s)]
        r = np.concatenate([model.residual(s, h, c[h]) for h in range(halves)], 1)
        model.sub = r.reshape(k, m, d // m).transpose(1, 0, 2).copy()
        return model
    from codematch.operators.encode import coarse_codes

    first = coarse_codes(df, model).selectExpr("half", "c", "id", "part", "row_number() OVER (PARTITION BY half, c ORDER BY id) AS r").where(F.col("r") <= k).collect()
    per, w = m // halves, d // m
    sub = np.full((halves, K, per, k, w), 1e6)
    for r in first:
        res = np.array(r.part) - coarse[r.half][r.c]
        for b in range(per):
            sub[r.half, r.c, b, r.r - 1] = res[b * w : (b + 1) * w]
    return CodeModel(m=m, coarse=coarse, sub=sub, rot=rot)
