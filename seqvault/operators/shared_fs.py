"""Open files of the shared folder from a Python worker, through whatever store its URI names."""

from __future__ import annotations

import re
import uuid

from pyarrow import fs


def resolve(uri: str) -> tuple[fs.FileSystem, str]:
    """File system and path of a URI; Hadoop's one-slash ``file:/x`` is accepted."""
    return fs.FileSystem.from_uri(re.sub(r"^file:/(?=[^/])", "file:///", uri) if ":" in uri else f"file://{uri}")


class AtomicFile:
    """Write under a name of this attempt, then move into place, so that retries and twins leave one whole file.

    In a store whose move does not replace, the file of an earlier attempt stays: attempts write the same bytes.
    """

    def __init__(self, uri: str):
        self.store, self.path = resolve(uri)
        self.attempt = f"{self.path}.{uuid.uuid4().hex[:8]}"

    def __enter__(self):
        self.store.create_dir(self.path.rpartition("/")[0], recursive=True)
        self.sink = self.store.open_output_stream(self.attempt)
        return self.sink

    def __exit__(self, kind, *_):
        if not self.sink.closed:
            self.sink.close()
        if kind is not None:
            self.store.delete_file(self.attempt)
            return
        try:
            self.store.move(self.attempt, self.path)
        except OSError:
            if self.store.get_file_info(self.path).type != fs.FileType.File:
                raise
            self.store.delete_file(self.attempt)
