"""Binary files in the shared folder, by address: works for any store that pyarrow opens."""

from __future__ import annotations

import os
import uuid
from functools import lru_cache


@lru_cache(8)
def _opened(base: str):
    from pyarrow import fs

    if "://" not in base and not base.startswith("file:"):
        return fs.LocalFileSystem(), base
    if base.startswith("file:"):
        return fs.LocalFileSystem(), "/" + base[5:].lstrip("/")
    return fs.FileSystem.from_uri(base)


def create(base: str, name: str, suffix: str, data: bytes) -> str:
    """Write a file under a name that no other attempt of the task uses; returns that name.

    Only names that a finished task reports count, so what a lost task left is never read."""
    store, root = _opened(base)
    store.create_dir(root, recursive=True)
    own = f"{name}-{uuid.uuid4().hex}{suffix}"
    with store.open_output_stream(f"{root}/{own}", compression=None) as out:
        out.write(data)
    return own


def open_file(base: str, name: str):
    """A random-access file."""
    store, root = _opened(base)
    return store.open_input_file(os.path.join(root, name))


def read_range(base: str, name: str, offset: int, length: int) -> bytes:
    with open_file(base, name) as f:
        f.seek(offset)
        return f.read(length)


def read_all(base: str, name: str) -> bytes:
    with open_file(base, name) as f:
        return f.read()
