"""Files of our own formats in the shared folder, written and read by tasks.

Each task attempt writes files under names of its own; only names in a committed index or manifest count, so a repeated
attempt leaves an unread file behind and nothing else.
"""

from __future__ import annotations

import uuid

from pyarrow import fs


def open_fs(root: str) -> tuple[fs.FileSystem, str]:
    return fs.FileSystem.from_uri(root)


class NewFile:
    def __init__(self, root: str, suffix: str):
        system, base = open_fs(root)
        system.create_dir(base, recursive=True)
        self.name = f"{uuid.uuid4().hex}{suffix}"
        self.stream = system.open_output_stream(f"{base}/{self.name}", compression=None)
        self.size = 0

    def write(self, data: bytes) -> int:
        """Where ``data`` begins."""
        at = self.size
        self.stream.write(data)
        self.size += len(data)
        return at

    def close(self) -> None:
        self.stream.close()
