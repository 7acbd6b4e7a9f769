"""Binary files in shared storage, written by tasks and read back through Spark's own reader."""

from __future__ import annotations

import os
import uuid


def write_bytes(uri: str, data: bytes) -> None:
    """Write a file whole or not at all; a repeated attempt of a task replaces it with the same bytes."""
    if "://" not in uri and not uri.startswith("file:"):
        uri = "file://" + uri
    if uri.startswith("file:"):
        path = "/" + uri[5:].lstrip("/")
        os.makedirs(os.path.dirname(path), exist_ok=True)
        part = f"{path}.{uuid.uuid4().hex}.part"
        with open(part, "wb") as f:
            f.write(data)
        os.replace(part, path)
        return
    from pyarrow import fs

    store, path = fs.FileSystem.from_uri(uri)
    part = f"{path}.{uuid.uuid4().hex}.part"
    store.create_dir(os.path.dirname(path), recursive=True)
    with store.open_output_stream(part) as f:
        f.write(data)
    store.move(part, path)


def read_bytes(uri: str) -> bytes:
    """Read a whole file of shared storage."""
    if "://" not in uri and not uri.startswith("file:"):
        uri = "file://" + uri
    if uri.startswith("file:"):
        with open("/" + uri[5:].lstrip("/"), "rb") as f:
            return f.read()
    from pyarrow import fs

    store, path = fs.FileSystem.from_uri(uri)
    with store.open_input_stream(path) as f:
        return f.read()
