"""Binary files in the shared folder, written and read by tasks through the file system that the folder's URI names."""

from __future__ import annotations

import contextlib
import uuid
from collections.abc import Iterator
from typing import BinaryIO


def _at(uri: str):
    from pyarrow import fs

    if uri.startswith("file:/") and not uri.startswith("file:///"):
        uri = "file:///" + uri[len("file:/") :].lstrip("/")
    if "://" not in uri:
        return fs.LocalFileSystem(), uri
    return fs.FileSystem.from_uri(uri)


@contextlib.contextmanager
def new_file(folder: str, stem: str, suffix: str) -> Iterator[tuple[str, BinaryIO]]:
    """A file under a name that no other attempt of the task uses.

    What a lost or repeated attempt leaves is never read: readers go by the names that finished tasks return.
    """
    system, path = _at(folder)
    system.create_dir(path, recursive=True)
    name = f"{stem}-{uuid.uuid4().hex[:12]}{suffix}"
    with system.open_output_stream(f"{path}/{name}", compression=None) as out:
        yield f"{folder.rstrip('/')}/{name}", out


@contextlib.contextmanager
def old_file(uri: str) -> Iterator[BinaryIO]:
    system, path = _at(uri)
    with system.open_input_file(path) as read:
        yield read
