"""Byte access to files by URI, from the driver and from executors."""

from __future__ import annotations

import os
import uuid

from pyarrow import fs


def resolve(uri: str) -> tuple[fs.FileSystem, str]:
    """The file system and path of a URI; a path without a scheme is local."""
    return fs.FileSystem.from_uri(uri) if "://" in uri or uri.startswith("file:") else (fs.LocalFileSystem(), uri)


def write_whole(uri: str, data: bytes) -> None:
    """Writes a file under another name and renames it, so a lost attempt leaves no part of it."""
    store, path = resolve(uri)
    folder, name = path.rsplit("/", 1)
    store.create_dir(folder, recursive=True)
    with store.open_output_stream(temporary := f"{folder}/.{name}.{uuid.uuid4().hex}") as out:
        out.write(data)
    store.move(temporary, path)


class RangeReader:
    """Reads byte ranges of a file that stays open."""

    def __init__(self, uri: str):
        store, path = resolve(uri)
        self._file = store.open_input_file(path)
        self.size = self._file.size()

    def read(self, offset: int, length: int) -> bytes:
        self._file.seek(offset)
        data = self._file.read(length)
        if len(data) != length:
            raise EOFError(f"{length} bytes at {offset} go beyond the end")
        return data

    def __enter__(self) -> RangeReader:
        return self

    def __exit__(self, *_) -> None:
        self._file.close()


def remove_tree(uri: str) -> None:
    store, path = resolve(uri)
    if store.get_file_info(path).type != fs.FileType.NotFound:
        store.delete_dir(path)


def join(uri: str, *names: str) -> str:
    return "/".join([uri.rstrip("/"), *names]) if "://" in uri else os.path.join(uri, *names)
