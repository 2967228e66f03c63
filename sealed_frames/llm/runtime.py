"""Session plumbing shared by the training-data operators.

Everything that has to outlive an executor is written below the folder named by
``spark.checkpoint.dir``; a machine-local folder is used only where that setting is absent (tests).
"""

from __future__ import annotations

import json
import os
import tempfile
import uuid
from urllib.parse import urlparse

import numpy as np

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

ROOT = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))


def ship(spark: SparkSession) -> None:
    """Let Python workers import this package even where the driver got it through ``sys.path``."""
    env = spark.sparkContext.environment
    have = [p for p in (env.get("PYTHONPATH") or "").split(":") if p]
    if ROOT not in have:
        env["PYTHONPATH"] = ":".join([ROOT, *have])


def bound_batches(spark: SparkSession, most: int = 4 << 20) -> None:
    """At most about ``most`` bytes a batch on the way to Python workers: 10,000 whole texts are tens of MB, which the
    executor and the worker hold several times. A bound that the session was given stays."""
    key, free = "spark.sql.execution.arrow.maxBytesPerBatch", str((1 << 31) - 2)
    if spark.conf.get(key, free) == free:
        spark.conf.set(key, str(most))


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared folder; one of our own only where the session names none and all tasks run in this
    process. A cluster without the setting raises an error: its machines share no local folder."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = os.path.join(tempfile.gettempdir(), f"sealed-frames-{os.getuid()}")
        spark.sparkContext.setCheckpointDir(f"file://{base}")
        base = f"file://{base}"
    return base.rstrip("/")


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def settle(df: DataFrame, name: str = "step") -> DataFrame:
    """Write ``df`` to the shared folder and read it again: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def small_side(df: DataFrame, most_rows: int) -> DataFrame:
    """A broadcast hint where the written table has at most ``most_rows`` rows, else ``df`` as it is
    (Spark then shuffles both sides and splits skewed partitions). ``df`` must be cheap to count."""
    return F.broadcast(df) if df.count() <= most_rows else df


def put_arrays(fs_path: str, arrays: dict[str, np.ndarray]) -> None:
    """Write arrays into one file: a JSON directory of fixed place, then 64-byte aligned bodies."""
    from pyarrow import fs

    where, place, at = {}, [], 1 << 12
    for name, a in arrays.items():
        a = np.ascontiguousarray(a)
        where[name] = [a.dtype.str, len(a), at]
        place.append((at, a))
        at += -(-a.nbytes // 64) * 64
    head = json.dumps(where).encode()
    system, path = fs.FileSystem.from_uri(fs_path)
    system.create_dir(path.rsplit("/", 1)[0], recursive=True)
    with system.open_output_stream(path) as out:
        out.write(head.ljust(1 << 12))
        for at, a in place:
            out.write(a.tobytes())
            out.write(bytes(-a.nbytes % 64))


def get_arrays(fs_path: str) -> dict[str, np.ndarray]:
    """Map the arrays of a file; read them where the folder is not a mounted one."""
    from pyarrow import fs

    if urlparse(fs_path).scheme in ("", "file"):
        raw = np.memmap(urlparse(fs_path).path, np.uint8, mode="r").view(np.ndarray)
    else:
        system, path = fs.FileSystem.from_uri(fs_path)
        with system.open_input_stream(path) as f:
            raw = np.frombuffer(f.read(), np.uint8)
    where = json.loads(raw[: 1 << 12].tobytes())
    return {k: raw[at : at + n * np.dtype(kind).itemsize].view(kind) for k, (kind, n, at) in where.items()}
