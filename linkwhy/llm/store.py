"""Arrays that tasks write to the shared folder and map into memory from it."""

from __future__ import annotations

import os
import tempfile
import uuid

import numpy as np

from .common import local_path, mkdirs


def put(base: str, name: str, arrays: dict[str, np.ndarray]) -> None:
    """Write arrays as one ``.npy`` file each, whole or not at all (a repeated task writes the same again)."""
    local = local_path(base)
    if local:
        mkdirs(local)
        for key, array in arrays.items():
            temporary = f"{local}/.{name}.{key}.{uuid.uuid4().hex}.npy"
            np.save(temporary, array)
            os.replace(temporary, f"{local}/{name}.{key}.npy")
        return
    import io

    from pyarrow import fs

    files, path = fs.FileSystem.from_uri(base)
    files.create_dir(path, recursive=True)
    for key, array in arrays.items():
        buffer = io.BytesIO()
        np.save(buffer, array)
        with files.open_output_stream(f"{path}/{name}.{key}.npy") as out:
            out.write(buffer.getvalue())


def mapped(base: str, name: str, key: str) -> np.ndarray | None:
    """A memory map of an array; None if there is no such file.

    From a store that is no local folder the file is copied once to the worker's own temporary
    folder and unlinked as soon as it is mapped, so nothing stays behind.
    """
    local = local_path(base)
    if local:
        path = f"{local}/{name}.{key}.npy"
        return np.load(path, mmap_mode="r") if os.path.exists(path) else None
    from pyarrow import fs

    files, path = fs.FileSystem.from_uri(base)
    path = f"{path}/{name}.{key}.npy"
    if files.get_file_info(path).type == fs.FileType.NotFound:
        return None
    with tempfile.NamedTemporaryFile(suffix=".npy", delete=False) as copy:
        with files.open_input_stream(path) as source:
            while chunk := source.read(1 << 22):
                copy.write(chunk)
    try:
        return np.load(copy.name, mmap_mode="r")
    finally:
        os.unlink(copy.name)
