"""Byte streams in a folder that executors share, by local path or by any URI that Arrow opens."""

from __future__ import annotations

import os
import uuid
from urllib.parse import unquote, urlparse

from pyarrow import fs


def _at(path: str) -> tuple[fs.FileSystem, str]:
    if "://" in path and not path.startswith("file:"):
        return fs.FileSystem.from_uri(path)
    return fs.LocalFileSystem(), unquote(urlparse(path).path) if path.startswith("file:") else path


def new_name(folder: str, kind: str) -> str:
    """A name no other task or attempt uses; only names that a task returns count as written."""
    return f"{folder}/{uuid.uuid4().hex}.{kind}"


def create(path: str):
    store, p = _at(path)
    if isinstance(store, fs.LocalFileSystem):
        os.makedirs(os.path.dirname(p), exist_ok=True)
    return store.open_output_stream(p, compression=None)


def open_at(path: str):
    store, p = _at(path)
    return store.open_input_file(p)
