"""Streams on the shared folder from Python workers, by the file system that its URI names."""

from __future__ import annotations

import posixpath
import uuid

import pyarrow.fs as pafs


def attempt_name(stem: str, suffix: str) -> str:
    """A name of its own for each attempt of a task: only names that a finished attempt returned are ever read."""
    return f"{stem}-{uuid.uuid4().hex}{suffix}"


class Folder:
    def __init__(self, uri: str):
        self.fs, self.base = pafs.FileSystem.from_uri(uri if "://" in uri or uri.startswith("file:") else "file://" + uri)

    @property
    def local(self) -> bool:
        return isinstance(self.fs, pafs.LocalFileSystem)

    def path(self, name: str) -> str:
        return posixpath.join(self.base, name)

    def make(self) -> None:
        self.fs.create_dir(self.base, recursive=True)

    def writer(self, name: str):
        return self.fs.open_output_stream(self.path(name), compression=None)

    def reader(self, name: str):
        return self.fs.open_input_stream(self.path(name), compression=None)

    def random(self, name: str):
        return self.fs.open_input_file(self.path(name))
