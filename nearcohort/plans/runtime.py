"""What every iterative or Python-backed operator needs from the cluster.

* ``Workspace``: durable intermediate tables.  Lineage is cut by writing Parquet into the
  folder that ``spark.checkpoint.dir`` names, so a lost executor costs a re-read and never
  a recomputation of earlier rounds.
* ``ship``: puts this package on the executors' import path and bounds Arrow batches by bytes.
* ``small``: broadcast behind a checked row bound.
* ``few_rows``: the driver's own rows, without a Python task for each use of them.
"""

from __future__ import annotations

import os
import re
import tempfile
import uuid
import zipfile
from collections.abc import Iterable

import pyarrow as pa
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

#: Rows below which a side of narrow rows (a few longs) may be broadcast.
BROADCAST_ROWS = 1_000_000
#: Bytes of one Arrow batch between the JVM and Python; a single larger row is its own batch.
ARROW_BYTES = 4 << 20
_ARROW = "spark.sql.execution.arrow.maxBytesPerBatch"

_shipped: set[str] = set()


def checkpoint_root(spark: SparkSession) -> str:
    """The shared folder of the session; a temporary one only in local mode where none is set (tests)."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        known = spark.sparkContext._jsc.sc().getCheckpointDir()
        root = known.get() if known.isDefined() else None
    if not root:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        root = "file://" + tempfile.mkdtemp(prefix="nearcohort-")
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")


def ship(spark: SparkSession) -> None:
    """Serve the package's sources to the executors, once per application.

    Texts differ in length by orders of magnitude, so a batch is bounded by bytes, not only by
    rows; a lower bound of the session stays.
    """
    if spark.conf.isModifiable(_ARROW):
        n, unit = re.match(r"(-?\d+)([kmg]?)", spark.conf.get(_ARROW).lower()).groups()
        if not 0 < int(n) << {"": 0, "k": 10, "m": 20, "g": 30}[unit] <= ARROW_BYTES:
            spark.conf.set(_ARROW, str(ARROW_BYTES))
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    top = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    path = os.path.join(tempfile.mkdtemp(), "nearcohort_src.zip")
    with zipfile.ZipFile(path, "w") as z:
        for d, _, names in os.walk(top):
            for n in names:
                if n.endswith(".py"):
                    full = os.path.join(d, n)
                    z.write(full, os.path.join("nearcohort", os.path.relpath(full, top)))
    spark.sparkContext.addPyFile(path)
    _shipped.add(app)


class Workspace:
    """A folder of durable intermediate tables for one run of one operator."""

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        self.path = f"{checkpoint_root(spark)}/{label}-{uuid.uuid4().hex[:12]}"
        self._n = 0

    def place(self, name: str) -> str:
        self._n += 1
        return f"{self.path}/{self._n:03d}-{name}"

    def save(self, df: DataFrame, name: str) -> DataFrame:
        """Write ``df`` and return the table read back: lineage ends here."""
        where = self.place(name)
        df.write.parquet(where)
        back = self.spark.read.schema(df.schema).parquet(where)
        back._workspace_path = where
        return back

    def save_count(self, df: DataFrame, name: str) -> tuple[DataFrame, int]:
        """``save`` and the number of rows, counted while they are written."""
        seen = Observation()
        back = self.save(df.observe(seen, F.count(F.lit(1)).alias("n")), name)
        return back, int(seen.get["n"])

    def drop(self, df: DataFrame | None) -> None:
        """Remove a saved table that nothing reads any more."""
        where = getattr(df, "_workspace_path", None)
        if where:
            self._remove(where)

    def clear(self) -> None:
        """Remove all tables of a run whose results are read."""
        self._remove(self.path)

    def _remove(self, where: str) -> None:
        p = self.spark._jvm.org.apache.hadoop.fs.Path(where)
        p.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(p, True)


def small(df: DataFrame, rows: int, limit: int = BROADCAST_ROWS) -> DataFrame:
    """Broadcast hint if the counted ``rows`` stay under ``limit``; otherwise a shuffle join."""
    return F.broadcast(df) if rows <= limit else df


def few_rows(spark: SparkSession, rows: Iterable[tuple], schema: str | StructType) -> DataFrame:
    """Few rows of the driver as a relation in the plan: Arrow, as plain rows are read by Python tasks wherever they are used."""
    kind = schema if isinstance(schema, StructType) else StructType.fromDDL(schema)
    fields, columns = to_arrow_schema(kind), list(zip(*rows, strict=True)) or [()] * len(kind)
    return spark.createDataFrame(pa.Table.from_arrays([pa.array(c, f.type) for c, f in zip(columns, fields, strict=True)], schema=fields), kind)
