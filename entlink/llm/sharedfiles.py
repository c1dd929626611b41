"""Binary files in the shared folder, reached by URI from driver and executors."""

from __future__ import annotations

import uuid
from contextlib import contextmanager

from entlink.storage import locate


@contextmanager
def publishing(uri: str):
    """A stream whose file appears under ``uri`` only when complete, so a retried task replaces it whole."""
    fs, path = locate(uri)
    fs.create_dir(path.rsplit("/", 1)[0], recursive=True)
    part = f"{path}.{uuid.uuid4().hex}.part"
    with fs.open_output_stream(part) as out:
        yield out
    fs.move(part, path)


def reading(uri: str):
    """A file open for random access."""
    fs, path = locate(uri)
    return fs.open_input_file(path)
