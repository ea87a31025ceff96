"""Files in the shared folder, written and read by executors: plain paths, file: addresses, or any store that pyarrow can open."""

from __future__ import annotations

import os
import uuid
from contextlib import contextmanager
from urllib.parse import unquote, urlparse


def local_path(uri: str) -> str | None:
    """The path of a plain or file: address, else None."""
    parsed = urlparse(uri)
    if parsed.scheme == "file":
        return unquote(parsed.path)
    return uri if not parsed.scheme else None


def _remote(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


@contextmanager
def written(uri: str):
    """A binary file that appears under its name only when it is whole, so that tasks may be repeated."""
    path = local_path(uri)
    if path:
        os.makedirs(os.path.dirname(path), exist_ok=True)
        part = f"{path}.{uuid.uuid4().hex}.part"
        try:
            with open(part, "wb") as f:
                yield f
            os.replace(part, path)
        finally:
            if os.path.exists(part):
                os.remove(part)
        return
    store, path = _remote(uri)
    store.create_dir(path.rpartition("/")[0])
    part = f"{path}.{uuid.uuid4().hex}.part"
    with store.open_output_stream(part) as f:
        yield f
    store.move(part, path)


def opened(uri: str):
    """A binary file that can be read and sought in."""
    path = local_path(uri)
    if path:
        return open(path, "rb")
    store, path = _remote(uri)
    return store.open_input_file(path)


def removed(uri: str) -> None:
    path = local_path(uri)
    if path:
        if os.path.exists(path):
            os.remove(path)
        return
    store, path = _remote(uri)
    store.delete_file(path)
