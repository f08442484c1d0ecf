"""Files in the shared folder, written by tasks under temporary names and committed by a rename.

A retried or speculative task writes the same bytes to a temporary name of its own and renames over the same final
name, so a lost executor leaves no half-written file behind a final name.
"""

from __future__ import annotations

import uuid


class Store:
    """``where`` is a URI that pyarrow's file systems know: ``file://`` or, on a cluster, ``hdfs://``, ``s3://``, ``gs://``."""

    def __init__(self, where: str):
        from pyarrow import fs

        self.fs, self.root = fs.FileSystem.from_uri(where)
        self._named: dict[int, tuple[str, str]] = {}

    def create(self, name: str):
        self.fs.create_dir(self.root, recursive=True)
        temporary = f"{self.root}/_temporary-{name}-{uuid.uuid4().hex}"
        f = self.fs.open_output_stream(temporary, compression=None)
        self._named[id(f)] = (temporary, f"{self.root}/{name}")
        return f

    def commit(self, f) -> None:
        f.close()
        self.fs.move(*self._named.pop(id(f)))

    def open(self, name: str):
        return self.fs.open_input_stream(f"{self.root}/{name}", compression=None, buffer_size=1 << 20)
