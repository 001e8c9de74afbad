"""Table access and the shared folder that lineage cuts go to."""

from __future__ import annotations

import tempfile
import uuid

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame, SparkSession


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The parquet table ``name`` below ``sf_dir``; only Spark's readers touch the path."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``. Only a local master, whose executors are the driver, may
    do without it and gets a folder of its own."""
    sc = spark.sparkContext
    told = spark.conf.get("spark.checkpoint.dir", None)
    if sc.getCheckpointDir() is None:
        if not told and not sc.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        sc.setCheckpointDir(told or tempfile.mkdtemp(prefix="tideline-"))
    return told or sc.getCheckpointDir()


def cut(df: DataFrame) -> DataFrame:
    """``df`` written to the shared folder, without its lineage; survives the loss of any executor."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def saved(df: DataFrame) -> DataFrame:
    """``df`` as a table in the shared folder. Unlike :func:`cut` it forgets how the rows were dealt, and with that the planner's guess of
    their size: what is read has the size of its files, so a loop of joins stays plannable."""
    path = f"{shared_dir(df.sparkSession)}/saved-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


class Store:
    """Cuts lineage like :func:`cut` and knows where each result lies, so that a loop can give back what it has left behind.

    The folder is watched around each write; where it can't be listed, or others write there at the same time, nothing is given back.
    """

    def __init__(self, spark: SparkSession):
        shared_dir(spark)
        self.held: list[tuple[DataFrame, str | None]] = []
        self.released = 0
        try:
            self.fs, self.path = pafs.FileSystem.from_uri(spark.sparkContext.getCheckpointDir())
        except (pa.ArrowException, ValueError, OSError):
            self.fs = None

    def _folders(self) -> set[str]:
        if self.fs is None:
            return set()
        return {f.path for f in self.fs.get_file_info(pafs.FileSelector(self.path, allow_not_found=True)) if f.type == pafs.FileType.Directory}

    def cut(self, df: DataFrame) -> DataFrame:
        before = self._folders()
        out = df.checkpoint(eager=True)
        new = self._folders() - before
        self.held.append((out, new.pop() if len(new) == 1 else None))
        return out

    def keep(self, *frames: DataFrame) -> None:
        """Deletes all that was cut so far but ``frames`` (by identity), which the caller still reads."""
        stay = [h for h in self.held if any(h[0] is f for f in frames)]
        for frame, folder in self.held:
            if folder and not any(frame is s[0] for s in stay):
                self.fs.delete_dir(folder)
                self.released += 1
        self.held = stay

    def pin(self) -> None:
        """What was cut so far is never deleted."""
        self.held = []
