"""Files in the shared folder, written and read by the executors."""

from __future__ import annotations

import posixpath
import uuid

from pyarrow import fs


def put(folder: str, data: bytes, suffix: str) -> str:
    """Writes a new file under a name no other attempt uses; returns its URI.

    A file counts only once its row stands in a saved manifest, so what a lost task
    leaves behind is never read.
    """
    where, path = fs.FileSystem.from_uri(folder)
    where.create_dir(path, recursive=True)
    name = f"{uuid.uuid4().hex}{suffix}"
    with where.open_output_stream(posixpath.join(path, name)) as out:
        out.write(data)
    return f"{folder}/{name}"


def get(uri: str) -> bytes:
    where, path = fs.FileSystem.from_uri(uri)
    with where.open_input_stream(path) as src:
        return src.read()
