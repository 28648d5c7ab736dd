"""Words of whole texts as bytes: ASCII lower-casing and splitting by one table, at C speed."""

from __future__ import annotations

# Upper case goes to lower case; the other bytes of each table's set separate words.
_LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
#: [^\x00-\x2F\x3A-\x60\x7B-\x7F]+ after lower-casing: ASCII letters and digits, and all beyond ASCII.
ALNUM = bytes(b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in _LOWER)
#: [^\x20\x09-\x0D]+ after lower-casing: whatever white space separates.
SPACED = bytes(32 if 9 <= b <= 13 else b for b in _LOWER)


def alnum_words(text: bytes | None) -> list[bytes]:
    """Runs of ASCII letters and digits and of all non-ASCII characters, lower-cased in A-Z."""
    return text.translate(ALNUM).split() if text else []


def spaced_words(text: bytes | None) -> list[bytes]:
    """Runs of anything but space, tab, newline, vertical tab, form feed and return, lower-cased in A-Z."""
    return text.translate(SPACED).split() if text else []


def spaced_bounds(text: bytes):
    """(starts, ends) of spaced_words(text) as byte offsets."""
    import numpy as np

    raw = np.frombuffer(text.translate(SPACED), np.uint8) != 32
    edge = np.diff(np.concatenate([[False], raw, [False]]).astype(np.int8))
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)


def alnum_bounds(text: bytes):
    """(starts, ends) of alnum_words(text) as byte offsets."""
    import numpy as np

    raw = np.frombuffer(text.translate(ALNUM), np.uint8) != 32
    edge = np.diff(np.concatenate([[False], raw, [False]]).astype(np.int8))
    return np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
