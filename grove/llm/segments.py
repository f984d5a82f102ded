"""Array files in the shared folder, written by tasks and memory-mapped by readers.

A file holds several arrays behind a small header. Writers go through Arrow's file
systems, under a new name at each attempt; a reader maps a file in place where the
folder is mounted, and otherwise maps a fetched copy that is unlinked at once, so
nothing stays behind on an executor.
"""

from __future__ import annotations

import json
import mmap
import os
import tempfile
import uuid

import numpy as np

_OPEN: dict[str, list[np.ndarray]] = {}


def _fs(folder: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(folder)


def put(folder: str, arrays: list[np.ndarray]) -> str:
    """Write the arrays as one new file; its name."""
    files, root = _fs(folder)
    files.create_dir(root, recursive=True)
    name = f"{uuid.uuid4().hex}.seg"
    head = json.dumps([[a.dtype.str, len(a)] for a in arrays]).encode()
    head += b" " * (-(len(head) + 8) % 64)
    with files.open_output_stream(f"{root}/{name}") as out:
        out.write(len(head).to_bytes(8, "little") + head)
        for a in arrays:
            raw = np.ascontiguousarray(a).tobytes()
            out.write(raw + b"\0" * (-len(raw) % 64))
    return name


def maps(folder: str, name: str) -> list[np.ndarray]:
    """The arrays of a file, memory-mapped and kept open in this process."""
    key = f"{folder}/{name}"
    if key not in _OPEN:
        files, root = _fs(folder)
        if files.type_name == "local":
            with open(f"{root}/{name}", "rb") as f:
                raw = mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ)
        else:
            fd, path = tempfile.mkstemp()
            with os.fdopen(fd, "r+b") as f, files.open_input_stream(f"{root}/{name}") as src:
                while block := src.read(1 << 22):
                    f.write(block)
                f.flush()
                raw = mmap.mmap(f.fileno(), 0, access=mmap.ACCESS_READ)
            os.unlink(path)
        n = int.from_bytes(raw[:8], "little")
        out, at = [], 8 + n
        for kind, count in json.loads(raw[8 : 8 + n]):
            a = np.frombuffer(raw, np.dtype(kind), count, at)
            out.append(a)
            at += a.nbytes + -a.nbytes % 64
        _OPEN[key] = out
    return _OPEN[key]


def forget(folder: str) -> None:
    for key in [k for k in _OPEN if k.startswith(folder + "/")]:
        del _OPEN[key]
