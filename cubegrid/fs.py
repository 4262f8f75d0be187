"""Small files and folders through Hadoop's file system, wherever the grid lives."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import SparkSession


def _fs(spark: SparkSession, path: str):
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), p


def exists(spark: SparkSession, path: str) -> bool:
    fs, p = _fs(spark, path)
    return fs.exists(p)


def delete(spark: SparkSession, path: str) -> None:
    fs, p = _fs(spark, path)
    fs.delete(p, True)


def size(spark: SparkSession, path: str) -> int:
    fs, p = _fs(spark, path)
    return fs.getContentSummary(p).getLength() if fs.exists(p) else 0


def names(spark: SparkSession, path: str) -> list[str]:
    """Names of what lies directly in a folder; none where there is no folder."""
    fs, p = _fs(spark, path)
    return sorted(s.getPath().getName() for s in fs.listStatus(p)) if fs.exists(p) else []


def list_files(spark: SparkSession, path: str) -> list[tuple[str, int]]:
    """(path, bytes) of the data files under a folder."""
    fs, p = _fs(spark, path)
    out, walk = [], fs.listFiles(p, True)
    while walk.hasNext():
        s = walk.next()
        if not s.getPath().getName().startswith(("_", ".")):
            out.append((s.getPath().toString(), s.getLen()))
    return sorted(out)


def read_text(spark: SparkSession, path: str) -> str:
    fs, p = _fs(spark, path)
    stream = fs.open(p)
    try:
        return bytes(spark.sparkContext._jvm.org.apache.commons.io.IOUtils.toByteArray(stream)).decode()
    finally:
        stream.close()


def publish_text(spark: SparkSession, path: str, text: str) -> bool:
    """Create a file with this content, whole or not at all; False if the name is taken.

    The content is written beside the target and given its name in one step that fails where the
    name exists: a hard link on a local disk, a rename elsewhere (atomic on HDFS and its like).
    """
    fs, p = _fs(spark, path)
    jvm = spark.sparkContext._jvm
    temp = jvm.org.apache.hadoop.fs.Path(p.getParent(), f".{p.getName()}.{uuid.uuid4().hex}")
    fs.mkdirs(p.getParent())
    stream = fs.create(temp, True)
    stream.write(bytearray(text.encode()))
    stream.close()
    try:
        if fs.getScheme() == "file":
            at = lambda x: jvm.java.nio.file.Path.of(x.toUri().getPath(), spark.sparkContext._gateway.new_array(jvm.String, 0))
            if fs.exists(p):
                return False
            try:
                jvm.java.nio.file.Files.createLink(at(p), at(temp))
            except Exception:  # taken in the meantime, or a disk without links
                if fs.exists(p):
                    return False
                raise
            return True
        return not fs.exists(p) and fs.rename(temp, p)
    finally:
        fs.delete(temp, False)


_OWN_ROOTS: dict[str, str] = {}


def shared_root(spark: SparkSession) -> str:
    """The folder that driver and executors share, as the session names it.

    Where ``spark.checkpoint.dir`` is unset, the folder given to ``setCheckpointDir`` is taken; a
    temporary folder of this machine stands in only where the whole application runs in one process.
    """
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    given = spark.sparkContext._jsc.sc().getCheckpointDir()
    if given.isDefined():
        return given.get().rstrip("/")
    if re.fullmatch(r"local(\[[^]]*\])?", spark.sparkContext.master) is None:
        raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
    app = spark.sparkContext.applicationId
    if app not in _OWN_ROOTS:
        _OWN_ROOTS[app] = f"file://{tempfile.mkdtemp(prefix='cubegrid-')}"
    return _OWN_ROOTS[app]


def scratch(spark: SparkSession, name: str) -> str:
    """A new folder path in the shared folder."""
    return f"{shared_root(spark)}/{name}-{uuid.uuid4().hex[:12]}"
