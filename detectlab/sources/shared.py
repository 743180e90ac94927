"""Plain files in the folder that the driver and all executors share."""

from __future__ import annotations

import re
import tempfile


def _local(uri: str) -> str | None:
    return re.sub("^file:/*", "/", uri) if ":" not in uri or uri.startswith("file:") else None


def opened(uri: str, mode: str):
    """A file of the local or a distributed file system: rb or wb."""
    if path := _local(uri):
        return open(path, mode)
    from pyarrow import fs

    store, path = fs.FileSystem.from_uri(uri)
    return store.open_input_stream(path) if mode == "rb" else store.open_output_stream(path)


def mapped(uri: str) -> memoryview:
    """The bytes of a file, as pages that the system loads and drops; of a distributed one, from a copy without a name."""
    import mmap
    import shutil

    with opened(uri, "rb") if _local(uri) else tempfile.TemporaryFile() as file:
        if not _local(uri):
            with opened(uri, "rb") as source:
                shutil.copyfileobj(source, file, 1 << 20)
            file.flush()
        file.seek(0, 2)
        return memoryview(mmap.mmap(file.fileno(), 0, access=mmap.ACCESS_READ)) if file.tell() else memoryview(b"")
