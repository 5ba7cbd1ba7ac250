"""Scratch tables in the folder all executors share; they cut the lineage of iterative plans."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_own: dict[str, str] = {}

#: Narrow rows up to which a counted side is broadcast.
BROADCAST_ROWS = 200_000
#: Vector bytes up to which a table of vectors goes to the tasks whole.
VECTOR_BYTES = 64 << 20


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``, or else the folder given to ``setCheckpointDir``.

    Where neither is set, a local master gets a temporary folder that goes at
    exit; on a cluster that is an error, as executors would write to their own
    disks and later reads would miss rows.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    given = spark.sparkContext._jsc.sc().getCheckpointDir()
    if given.isDefined():
        return given.get().rstrip("/")
    if not is_local(spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    app = spark.sparkContext.applicationId
    if app not in _own:
        folder = tempfile.mkdtemp(prefix="semtrie-shared-")
        atexit.register(shutil.rmtree, folder, ignore_errors=True)
        _own[app] = "file://" + folder
    return _own[app]


def is_local(master: str) -> bool:
    return master == "local" or master.startswith("local[")


def materialize(df: DataFrame, tag: str) -> DataFrame:
    """Cut the lineage by writing ``df`` into the shared folder and reading it again."""
    path = f"{shared_dir(df.sparkSession)}/semtrie/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._scratch_path = path
    return out


def discard(df: DataFrame | None) -> None:
    """Remove a scratch table that nothing reads any more."""
    path = getattr(df, "_scratch_path", None)
    if path is None:
        return
    spark = df.sparkSession
    hadoop_path = spark._jvm.org.apache.hadoop.fs.Path(path)
    hadoop_path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(hadoop_path, True)


def small(df: DataFrame, limit: int = BROADCAST_ROWS) -> DataFrame:
    """Broadcast hint behind a count; beyond ``limit`` rows the join shuffles."""
    return F.broadcast(df) if df.count() <= limit else df


def sent_vectors(vectors: DataFrame):
    """A broadcast (ids, matrix), in id order, of a table (id, vector) counted to be small; None where it is not.

    Vectors are packed or arrays of doubles.  Also None for ids that are no integers or repeat, and for vectors of
    several lengths or with nulls inside: such tables are joined.
    """
    found = small_vectors(vectors)
    return None if found is None else vectors.sparkSession.sparkContext.broadcast(found)


def small_vectors(vectors: DataFrame) -> tuple[np.ndarray, np.ndarray] | None:
    """What ``sent_vectors`` sends, at the driver."""
    key, col = vectors.columns
    if dict(vectors.dtypes)[key] not in ("bigint", "int"):
        return None
    known = vectors.filter(F.col(key).isNotNull() & F.col(col).isNotNull())
    packed = dict(vectors.dtypes)[col] == "binary"
    width = F.octet_length(col) if packed else F.size(col) * 8
    n, size, least, most = known.agg(F.count(F.lit(1)), F.coalesce(F.sum(width), F.lit(0)), F.min(width), F.max(width)).first()
    if not n or size > VECTOR_BYTES or least != most or not most:
        return None
    rows = known.toArrow()
    ids = rows.column(key).to_numpy().astype(np.int64)
    order = np.argsort(ids, kind="stable")
    ids = ids[order]
    if (ids[1:] == ids[:-1]).any():
        return None
    if packed:
        x = np.frombuffer(b"".join(rows.column(col).to_pylist()), dtype="<f8")
    else:
        flat = rows.column(col).combine_chunks().flatten()
        if flat.null_count:
            return None
        x = flat.to_numpy()
    return ids, x.reshape(n, -1)[order]


def places(ids: np.ndarray, of: np.ndarray) -> np.ndarray:
    """Where each value stands in ``ids`` (in order, without repeats); -1 for those not there."""
    if not len(ids):
        return np.full(len(of), -1)
    at = np.minimum(np.searchsorted(ids, of), len(ids) - 1)
    return np.where(ids[at] == of, at, -1)
