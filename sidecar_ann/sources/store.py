"""Objects in a store, by path or URI: written once, read by range. Usable on driver and executors."""

from __future__ import annotations

import atexit
import os
import uuid

import pyarrow.fs as pafs


def resolve(path: str):
    if "://" in path or path.startswith("file:"):
        return pafs.FileSystem.from_uri(path.replace("s3a://", "s3://", 1))
    return pafs.LocalFileSystem(), path


def put(path: str, data: bytes) -> None:
    """Whole or not at all: a name of its own first, then a move."""
    fs, p = resolve(path)
    fs.create_dir(p.rsplit("/", 1)[0], recursive=True)
    part = f"{p}.{uuid.uuid4().hex}.part"
    with fs.open_output_stream(part) as f:
        f.write(data)
    fs.move(part, p)


def put_if_absent(path: str, data: bytes) -> bool:
    """Creates the object unless it exists; False if it does. Exclusive on local file systems by the open mode and
    through a hard link of a whole file; stores with conditional writes offer the same by their own means."""
    fs, p = resolve(path)
    if isinstance(fs, pafs.LocalFileSystem):
        os.makedirs(p.rsplit("/", 1)[0], exist_ok=True)
        part = f"{p}.{uuid.uuid4().hex}.part"
        with open(part, "wb") as f:
            f.write(data)
        try:
            os.link(part, p)
            return True
        except FileExistsError:
            return False
        finally:
            os.unlink(part)
    if fs.get_file_info(p).type != pafs.FileType.NotFound:
        return False
    put(path, data)
    return True


def get(path: str, offset: int = 0, length: int | None = None) -> bytes:
    fs, p = resolve(path)
    with fs.open_input_file(p) as f:
        return f.read_at(f.size() - offset if length is None else length, offset)


def opened(path: str):
    """The object as a file to be read by range; closed by its `with`."""
    fs, p = resolve(path)
    return fs.open_input_file(p)


def size(path: str) -> int:
    fs, p = resolve(path)
    return fs.get_file_info(p).size


def listing(folder: str) -> list[tuple[str, int, float]]:
    """(name, bytes, seconds since the epoch) of the objects of a folder."""
    fs, p = resolve(folder)
    found = fs.get_file_info(pafs.FileSelector(p, allow_not_found=True))
    return sorted((x.base_name, x.size, x.mtime.timestamp()) for x in found if x.type == pafs.FileType.File)


def walk(folder: str) -> list[tuple[str, float]]:
    """(path below the folder, seconds since the epoch) of all objects at any depth."""
    fs, p = resolve(folder)
    found = fs.get_file_info(pafs.FileSelector(p, recursive=True, allow_not_found=True))
    return sorted((x.path[len(p.rstrip("/")) + 1 :], x.mtime.timestamp()) for x in found if x.type == pafs.FileType.File)


def delete(path: str) -> None:
    fs, p = resolve(path)
    fs.delete_file(p)


_left: list[str] = []


def delete_at_exit(folder: str) -> None:
    _left.append(folder)


@atexit.register
def _clean() -> None:
    for folder in _left:
        fs, p = resolve(folder)
        if fs.get_file_info(p).type == pafs.FileType.Directory:
            fs.delete_dir(p)
