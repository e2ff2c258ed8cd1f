"""A table function that cuts a text into windows of words."""

from __future__ import annotations


class TextWindows:
    def eval(self, text: str, width: int, step: int):
        words = (text or "").split()
        for at in range(0, max(1, len(words) - width + 1), step):
            yield at, " ".join(words[at : at + width])
