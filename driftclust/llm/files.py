"""Plain files in whatever store holds a folder, from Python tasks."""

from __future__ import annotations

import pyarrow.fs as pafs


def open_store(uri: str) -> tuple[pafs.FileSystem, str]:
    """File system and path of a URI such as file:///x, hdfs://n/x or s3://b/x."""
    if "://" not in uri and not uri.startswith("/"):
        uri = uri.replace("file:", "file://", 1)
    if uri.startswith("file:/") and not uri.startswith("file://"):
        uri = "file://" + uri[5:]
    if uri.startswith("/"):
        return pafs.LocalFileSystem(), uri
    return pafs.FileSystem.from_uri(uri)


def task_name(prefix: str, suffix: str) -> str:
    """A name that no other task, attempt or stage uses."""
    import uuid

    from pyspark import TaskContext

    t = TaskContext.get()
    return f"{prefix}-{t.partitionId() if t else 0:06d}-{uuid.uuid4().hex}{suffix}"
