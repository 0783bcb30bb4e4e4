"""Text values as one buffer with an offset table, next to the array of strings that shards store."""

from __future__ import annotations

import numpy as np


class TextBuffer:
    """``get(i)`` is the i-th text or attribute value, cut from a single UTF-8 buffer."""

    def __init__(self, texts: list[str]):
        data = [t.encode() for t in texts]
        self.buffer = b"".join(data)
        self.offsets = np.concatenate([[0], np.cumsum([len(d) for d in data])]).astype(np.int64)

    def __len__(self) -> int:
        return len(self.offsets) - 1

    def __getitem__(self, i: int) -> str:
        if not 0 <= i < len(self):
            raise IndexError(i)
        return self.buffer[self.offsets[i] : self.offsets[i + 1]].decode()

    def bytes(self) -> int:
        return len(self.buffer) + 8 * len(self.offsets)
