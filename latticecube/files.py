"""Small driver-side files on whatever file system a path names."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import SparkSession


class Conflict(RuntimeError):
    """A file of that name exists."""


class Files:
    def __init__(self, spark: SparkSession, root: str):
        self.spark, self.root = spark, root.rstrip("/")
        self.jvm, self.conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()

    def path(self, name: str):
        return self.jvm.org.apache.hadoop.fs.Path(name)

    def fs(self):
        return self.path(self.root).getFileSystem(self.conf)

    def create(self, name: str, body: str) -> None:
        """Write a file that must not exist yet, in one visible step."""
        fs, tmp, to = self.fs(), self.path(f"{self.root}/{name}.{uuid.uuid4().hex}.tmp"), self.path(f"{self.root}/{name}")
        out = fs.create(tmp, True)
        out.write(bytearray(body.encode()))
        out.close()
        try:
            context = self.jvm.org.apache.hadoop.fs.FileContext.getFileContext(fs.getUri(), self.conf)
            context.rename(tmp, to, self.spark.sparkContext._gateway.new_array(self.jvm.org.apache.hadoop.fs.Options.Rename, 0))
        except Exception as e:
            fs.delete(tmp, False)
            raise Conflict(name) from e

    def read(self, name: str) -> str:
        stream = self.fs().open(self.path(f"{self.root}/{name}"))
        try:
            return self.jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8")
        finally:
            stream.close()

    def names(self, folder: str) -> list[str]:
        fs, at = self.fs(), self.path(f"{self.root}/{folder}")
        return sorted(s.getPath().getName() for s in fs.listStatus(at)) if fs.exists(at) else []

    def sizes(self, folder: str) -> dict[str, int]:
        """Bytes of each file of a folder, none where there is no such folder."""
        fs, at = self.fs(), self.path(f"{self.root}/{folder}")
        return {s.getPath().getName(): int(s.getLen()) for s in fs.listStatus(at) if s.isFile()} if fs.exists(at) else {}

    def size(self, name: str) -> int:
        fs, at = self.fs(), self.path(name)
        return int(fs.getContentSummary(at).getLength()) if fs.exists(at) else 0

    def delete(self, name: str) -> None:
        self.fs().delete(self.path(name), True)


def scratch_dir(spark: SparkSession) -> str:
    """A folder that driver and executors share: ``spark.checkpoint.dir``; only a local master may do without, with a folder of its machine."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        root = "file://" + tempfile.mkdtemp(prefix="latticecube-")
    return f"{root.rstrip('/')}/latticecube/{uuid.uuid4().hex}"
