"""Binary files that Python workers write to and read from the shared folder, whatever store holds it."""

from __future__ import annotations

import posixpath
import uuid

from pyarrow import fs
from pyspark.sql import SparkSession

from longweave.llm.common import shared_dir


def new_folder(spark: SparkSession, what: str) -> str:
    return posixpath.join(shared_dir(spark), f"{what}-{uuid.uuid4().hex}")


def open_store(uri: str):
    """(file system, path) of a URI or an absolute path."""
    return fs.FileSystem.from_uri(uri if "://" in uri or uri.startswith("file:") else f"file://{uri}")


class Publish:
    """A file that appears under its name only when whole: a retried or doubled task replaces it by the same bytes."""

    def __init__(self, uri: str):
        self.store, self.path = open_store(uri)
        self.store.create_dir(posixpath.dirname(self.path), recursive=True)
        self.draft = f"{self.path}.{uuid.uuid4().hex}.part"
        self.out = self.store.open_output_stream(self.draft, compression=None)
        self.size = 0

    def write(self, data: bytes) -> None:
        self.out.write(data)
        self.size += len(data)

    def publish(self) -> None:
        self.out.close()
        self.store.move(self.draft, self.path)


def remove(uri: str) -> None:
    store, path = open_store(uri)
    store.delete_dir(path)
