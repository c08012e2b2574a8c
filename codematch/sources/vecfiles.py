"""Vector benchmark files: each vector is its length (int32) and its numbers (float32 or uint8), little-endian.

Files are read by the engine's binary reader, so any store that it opens will do; a file is
one task's work, and large collections are kept as many files. write_fvecs writes one file
per partition through the same file system layer and keeps the ids in the file's name.
"""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def parse(content: bytes, kind: str = "fvecs") -> np.ndarray:
    """(n, d) of a whole file; an error if it is cut short."""
    if not content:
        return np.empty((0, 0))
    d = int(np.frombuffer(content[:4], "<i4")[0])
    width = 4 + d * (4 if kind == "fvecs" else 1)
    if d <= 0 or len(content) % width:
        raise ValueError("not a whole number of vectors")
    rows = np.frombuffer(content, np.uint8).reshape(-1, width)
    return rows[:, 4:].copy().view("<f4" if kind == "fvecs" else np.uint8).astype(np.float32)


def read_fvecs(spark: SparkSession, path: str, kind: str = "fvecs") -> DataFrame:
    """(id, vec) of all files under path: id is the file's first id (its name up to the dash) plus the place in it."""
    files = spark.read.format("binaryFile").option("pathGlobFilter", f"*.{kind}").load(path).select("path", "content")

    def run(batches):
        for batch in batches:
            for name, content in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                x = parse(content, kind)
                first = int(name.rsplit("/", 1)[1].split("-")[0] or 0)
                for at in range(0, len(x), 4096):
                    part = x[at : at + 4096]
                    yield pa.RecordBatch.from_arrays([pa.array(np.arange(first + at, first + at + len(part))), pa.array(list(part), pa.list_(pa.float32()))], names=["id", "vec"])

    return files.mapInArrow(run, "id long, vec array<float>")


def write_fvecs(df: DataFrame, path: str) -> None:
    """Files of (id, vec), a run of consecutive ids each."""

    def run(batches):
        store, root = fs.FileSystem.from_uri(path)
        store.create_dir(root, recursive=True)
        for batch in batches:
            ids = batch.column(0).to_numpy()
            vecs = batch.column(1).to_pylist()
            order = np.argsort(ids, kind="stable")
            cuts = np.flatnonzero(np.diff(ids[order]) != 1) + 1
            for own in np.split(order, cuts):
                if len(own):
                    with store.open_output_stream(f"{root}/{ids[own[0]]}-{uuid.uuid4().hex}.fvecs") as f:
                        f.write(b"".join(np.array([len(vecs[i])], "<i4").tobytes() + np.array(vecs[i], "<f4").tobytes() for i in own))
        yield pa.RecordBatch.from_pydict({"n": [1]})

    df.select("id", "vec").mapInArrow(run, "n long").agg(F.sum("n")).collect()
