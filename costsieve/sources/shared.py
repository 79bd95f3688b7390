"""Tables on the cluster's shared folder, which cut lineage and outlive executors, and this package on the workers."""

from __future__ import annotations

import os
import tempfile
import threading
import uuid
import zipfile
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

FALLBACK_DIR = "/tmp/checkpoints"


def shared_dir(spark: SparkSession) -> str:
    """The folder named by spark.checkpoint.dir. Only a session that runs on this machine alone may do without it."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    return (named or FALLBACK_DIR).rstrip("/")


class Staging:
    """A private folder below the shared one that holds the tables of one operator run.

    Results are lazy, so only the caller knows when the tables have served: ``with Staging.collected() as made`` lists what the block's operators have staged, and
    ``with Staging.scope()`` also deletes it at the block's end.
    """

    _here = threading.local()

    def __init__(self, spark: SparkSession, purpose: str):
        self.spark = spark
        self.path = f"{shared_dir(spark)}/costsieve/{purpose}-{uuid.uuid4().hex}"
        for made in getattr(Staging._here, "lists", ()):
            made.append(self)

    def table(self, df: DataFrame, name: str) -> DataFrame:
        """Write ``df`` once and return the scan of what was written."""
        place = f"{self.path}/{name}-{uuid.uuid4().hex[:8]}"
        df.write.option("compression", "zstd").parquet(place)
        return self.spark.read.schema(df.schema).parquet(place)

    def drop(self) -> None:
        """Delete the tables. Call it only when every result derived from them has been written."""
        jvm = self.spark.sparkContext._jvm
        where = jvm.org.apache.hadoop.fs.Path(self.path)
        where.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)

    @classmethod
    @contextmanager
    def collected(cls):
        """The list of all that this thread stages inside the block."""
        lists = cls._here.__dict__.setdefault("lists", [])
        made: list[Staging] = []
        lists.append(made)
        try:
            yield made
        finally:
            lists[:] = [x for x in lists if x is not made]

    @classmethod
    @contextmanager
    def scope(cls):
        """Delete at its end what the block has staged. Results must have been written or collected by then."""
        with cls.collected() as made:
            try:
                yield made
            finally:
                for one in made:
                    one.drop()


def ship(spark: SparkSession) -> None:
    """Send this package to the executors, once per session, so that Python workers can import it."""
    if getattr(spark.sparkContext, "_costsieve_shipped", False):
        return
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    name = os.path.basename(root)
    archive = os.path.join(tempfile.mkdtemp(prefix="costsieve-"), f"{name}.zip")
    with zipfile.ZipFile(archive, "w") as out:
        for folder, _, files in os.walk(root):
            for file in sorted(files):
                if file.endswith(".py"):
                    full = os.path.join(folder, file)
                    out.write(full, os.path.join(name, os.path.relpath(full, root)))
    spark.sparkContext.addPyFile(archive)
    spark.sparkContext._costsieve_shipped = True
