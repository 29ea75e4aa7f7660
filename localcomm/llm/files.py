"""Files in shared folders, opened from executors by whatever file system their address names."""

from __future__ import annotations

import uuid

import pyarrow.fs as pafs


def opened(path: str) -> tuple[pafs.FileSystem, str]:
    """The file system and the path in it; plain paths are local."""
    return pafs.FileSystem.from_uri(path) if ":/" in path else (pafs.LocalFileSystem(), path)


class Roller:
    """Writes numbered files of at most about `limit` bytes into a folder, under names that no other attempt uses.

    Only rows of the attempt that Spark commits name a file, so what a lost attempt left is never read.
    """

    def __init__(self, folder: str, limit: int, suffix: str):
        self.fs, self.folder = opened(folder)
        self.base, self.limit, self.suffix = folder.rstrip("/"), limit, suffix
        self.out = None
        self.name, self.at = "", 0
        self.fs.create_dir(self.folder, recursive=True)

    def write(self, data: bytes) -> tuple[str, int]:
        """The file's address and the offset that the data have in it."""
        if self.out is None:
            name = f"{uuid.uuid4().hex}{self.suffix}"
            self.name, self.at = f"{self.base}/{name}", 0
            self.out = self.fs.open_output_stream(f"{self.folder.rstrip('/')}/{name}", compression=None)
        at = self.at
        self.out.write(data)
        self.at += len(data)
        return self.name, at

    @property
    def full(self) -> bool:
        return self.at >= self.limit

    def close(self) -> None:
        if self.out is not None:
            self.out.close()
            self.out = None
            self.at = 0


class Reader:
    """Random reads from many files, keeping a few open."""

    def __init__(self, most: int = 16):
        self.most, self.files = most, {}

    def read(self, path: str, at: int, size: int) -> bytes:
        f = self.files.pop(path, None)
        if f is None:
            fs, inner = opened(path)
            f = fs.open_input_file(inner)
            if len(self.files) >= self.most:
                self.files.pop(next(iter(self.files))).close()
        self.files[path] = f
        return f.read_at(size, at)

    def size(self, path: str) -> int:
        self.read(path, 0, 0)
        return self.files[path].size()
