"""Shared scratch folders, reached through Hadoop's file system API so that any scheme works."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``, read from the session.

    Only where the session names none and runs in local mode is a temporary folder set instead.
    """
    context = spark.sparkContext
    named = context.getConf().get("spark.checkpoint.dir") or context.getCheckpointDir()
    if not named:
        if not context.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        named = tempfile.mkdtemp(prefix="ranksort-")
        context.setCheckpointDir(named)
    return named.rstrip("/")


def scratch(spark: SparkSession, label: str) -> str:
    """A new folder name under the shared root; nothing is created."""
    return f"{shared_root(spark)}/{label}-{uuid.uuid4().hex}"


#: Rows of a table of ids that one task writes, and tasks at least.
_ROWS_A_FILE, _FILES = 500_000, 8


def materialize(df: DataFrame, label: str, rows: int | None = None) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: cuts the lineage and survives lost executors.

    rows: about how many short rows there are, where that is known: they are then written by as many tasks
    as they need, and not in a file a shuffle partition.
    """
    spark = df.sparkSession
    path = scratch(spark, label)
    (df if rows is None else df.coalesce(max(_FILES, rows // _ROWS_A_FILE))).write.parquet(path)
    kept = spark.read.schema(df.schema).parquet(path)
    kept.scratch_path = path
    return kept


def release(*tables: DataFrame) -> None:
    """Delete what ``materialize`` wrote, once nothing that is still to be run reads it."""
    for table in tables:
        Files(table.sparkSession, table.scratch_path).remove(table.scratch_path)


def unused(columns: list[str], name: str) -> str:
    """``name``, or with underscores before it, so that no column has it."""
    taken = {c.lower() for c in columns}
    while name in taken:
        name = f"_{name}"
    return name


class Files:
    """The few file operations the operators need on the driver."""

    def __init__(self, spark: SparkSession, root: str):
        self._jvm = spark._jvm
        self._conf = spark._jsc.hadoopConfiguration()
        self.root = self.path(root).getFileSystem(self._conf).makeQualified(self.path(root)).toString()
        self._fs = self.path(self.root).getFileSystem(self._conf)

    def path(self, name: str):
        return self._jvm.org.apache.hadoop.fs.Path(name)

    def at(self, *parts: str) -> str:
        return "/".join((self.root, *parts))

    def make(self, folder: str) -> None:
        self._fs.mkdirs(self.path(folder))

    def names(self, folder: str) -> list[str]:
        if not self._fs.exists(self.path(folder)):
            return []
        return sorted(s.getPath().getName() for s in self._fs.listStatus(self.path(folder)))

    def sizes(self, folder: str) -> dict[str, int]:
        """Bytes by name of the data files in a folder."""
        if not self._fs.exists(self.path(folder)):
            return {}
        found = self._fs.listStatus(self.path(folder))
        return {s.getPath().getName(): s.getLen() for s in found if not s.getPath().getName().startswith(("_", "."))}

    def read(self, name: str) -> str:
        stream = self._fs.open(self.path(name))
        try:
            return self._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8")
        finally:
            stream.close()

    def write(self, name: str, text: str) -> None:
        stream = self._fs.create(self.path(name), True)
        try:
            stream.write(bytearray(text.encode()))
        finally:
            stream.close()

    def publish(self, source: str, target: str) -> bool:
        """Rename in one step; False if the target is there already."""
        context = self._jvm.org.apache.hadoop.fs.FileContext.getFileContext(self.path(self.root).toUri(), self._conf)
        none = self._jvm.org.apache.hadoop.fs.Options.Rename.NONE
        options = self._jvm.java.lang.reflect.Array.newInstance(none.getClass(), 1)
        options[0] = none
        try:
            context.rename(self.path(source), self.path(target), options)
            return True
        except Exception as error:
            if "FileAlreadyExists" in str(error) or self._fs.exists(self.path(target)):
                return False
            raise

    def remove(self, name: str) -> None:
        self._fs.delete(self.path(name), True)
