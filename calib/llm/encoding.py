"""Cutting texts where byte-level BPE may be done piece by piece.

The splitting pattern always cuts before a single space that stands between two other characters, so the
ids of a text are the ids of its first chunk followed by those of each further chunk with its space in front.
"""

from __future__ import annotations

import re
import numpy as np

#: White space beside the space and line feed.
ODD_BLANK = re.compile("[\t\x0b\x0c\r\x1c-\x1f\x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]")
_INNER_SPACE = re.compile(r"(?<=\S) (?=\S)")
#: Chunks longer than this are encoded each time and never kept.
LONGEST_KEPT = 48


def space_chunks(text: str) -> list[str]:
    """Pieces between those spaces at which every text may be cut."""
    if text[:1] == " " or text[-1:] == " " or "  " in text or " \n" in text or "\n " in text or ODD_BLANK.search(text):
        return _INNER_SPACE.split(text)
    return text.split(" ")


def le32(ids) -> bytes:
    return np.asarray(ids, dtype="<u4").tobytes()
