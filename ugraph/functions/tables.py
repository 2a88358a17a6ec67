"""Written intermediate tables and the portable pseudo-random number."""

from __future__ import annotations

import atexit
import os
import shutil
import tempfile
import uuid
import zipfile

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

MODULUS = 1000003
EPS = 1e-12
_LOCAL: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local["):
        return spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_work"
    if not _LOCAL:
        _LOCAL.append(tempfile.mkdtemp(prefix="ugraph-"))
        atexit.register(shutil.rmtree, _LOCAL[0], ignore_errors=True)
    return _LOCAL[0]


def materialise(df: DataFrame, tag: str) -> DataFrame:
    """Write to the shared folder and read back; cuts lineage and outlives lost executors."""
    path = f"{shared_dir(df.sparkSession)}/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


_SHIPPED: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Give the executors this package where their Python path lacks it."""
    root = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    known = [os.path.abspath(p) for p in os.environ.get("PYTHONPATH", "").split(os.pathsep) if p]
    app = spark.sparkContext.applicationId
    if root in known or app in _SHIPPED:
        return
    archive = os.path.join(tempfile.mkdtemp(), "ugraph_code.zip")
    with zipfile.ZipFile(archive, "w") as z:
        for folder, _, names in os.walk(os.path.join(root, "ugraph")):
            for n in names:
                if n.endswith(".py"):
                    full = os.path.join(folder, n)
                    z.write(full, os.path.relpath(full, root))
    spark.sparkContext.addPyFile(archive)
    _SHIPPED.add(app)


def u(k: Column, salt: int) -> Column:
    """A number in [0, 1) from an integer key, equal in Spark and SQL: a cubic map modulo MODULUS."""
    x = ((k.cast("long") % MODULUS) * 7919 + salt * 104729) % MODULUS
    y = (((x * x) % MODULUS) * x + x * 48611) % MODULUS
    return y.cast("double") / F.lit(float(MODULUS))


def u_sql(k: str, salt: int) -> str:
    x = f"(((({k}) % {MODULUS}) * 7919 + {salt * 104729}) % {MODULUS})"
    return f"(CAST(((({x} * {x}) % {MODULUS}) * {x} + 48611 * {x}) % {MODULUS} AS DOUBLE) / CAST({MODULUS} AS DOUBLE))"
