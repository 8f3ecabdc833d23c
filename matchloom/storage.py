"""Where intermediate tables live, and how lineage is cut.

Intermediate tables are Parquet files under the folder that the cluster names in
``spark.checkpoint.dir``; every executor and the driver can read them, so a lost
executor costs a re-read and not a recomputation.
"""

from __future__ import annotations

import atexit
import uuid

from pyspark.sql import DataFrame, SparkSession

_TEST_DIR = "/tmp/checkpoints/matchloom"
_written: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The shared folder named by the session. Where none is set, a folder of our own in local mode,
    as in tests, and an error on a cluster, whose machines share no such folder."""
    if named := spark.conf.get("spark.checkpoint.dir", None):
        return named
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all machines share")
    return f"file://{_TEST_DIR}"


def _delete(spark: SparkSession, path: str) -> None:
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(hadoop, True)


@atexit.register
def _sweep() -> None:
    for spark, path in _written:
        try:
            if spark.sparkContext._jsc is not None:
                _delete(spark, path)
        except Exception:  # the session may be gone at interpreter exit
            return


class Scratch:
    """Written tables of one run. ``save`` writes and rereads, ``drop`` frees early, ``drop_others``
    all tables but those given."""

    def __init__(self, spark: SparkSession, label: str):
        self.spark = spark
        self.root = f"{shared_dir(spark).rstrip('/')}/{label}-{uuid.uuid4().hex}"
        self.count = 0
        self.kept: dict[str, DataFrame] = {}
        _written.append((spark, self.root))

    def save(self, df: DataFrame, name: str = "t", codec: str | None = None) -> DataFrame:
        self.count += 1
        path = f"{self.root}/{self.count}-{name}"
        df.write.parquet(path, compression=codec)
        kept = self.spark.read.schema(df.schema).parquet(path)
        kept._scratch_path = path
        kept._orders = {}  # of a table of edges: see edges.ordered_edges
        self.kept[path] = kept
        return kept

    def drop(self, *frames: DataFrame) -> None:
        for df in frames:
            if path := getattr(df, "_scratch_path", None):
                _delete(self.spark, path)
                self.kept.pop(path, None)

    def drop_others(self, *needed: DataFrame) -> None:
        paths = {getattr(df, "_scratch_path", None) for df in needed}
        self.drop(*[df for path, df in self.kept.items() if path not in paths])
