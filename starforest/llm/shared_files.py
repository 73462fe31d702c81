"""Files in a folder that all executors share, by URI."""

from __future__ import annotations

import re
import uuid

from pyarrow import fs as pafs


def open_store(uri: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(re.sub(r"^file:/+", "file:///", uri))


def write_whole(uri: str, *parts: bytes) -> None:
    """All or nothing: a retried task replaces its file, a lost one leaves none under this name."""
    fs, path = open_store(uri)
    fs.create_dir(path.rpartition("/")[0], recursive=True)
    half = f"{path}.{uuid.uuid4().hex}.tmp"
    with fs.open_output_stream(half) as out:
        for p in parts:
            out.write(p)
    fs.move(half, path)


def read_range(uri: str, at: int, size: int) -> bytes:
    fs, path = open_store(uri)
    with fs.open_input_file(path) as f:
        f.seek(at)
        return f.read(size)


def size_of(uri: str) -> int:
    fs, path = open_store(uri)
    return fs.get_file_info(path).size


def read_whole(uri: str) -> bytes:
    fs, path = open_store(uri)
    with fs.open_input_file(path) as f:
        return f.read()


def remove_tree(uri: str) -> None:
    fs, path = open_store(uri)
    if fs.get_file_info(path).type != pafs.FileType.NotFound:
        fs.delete_dir(path)
