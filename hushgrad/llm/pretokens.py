r"""Pre-token boundaries of whole batches, in vectorised numpy.

Two splitting patterns of public tokenizers are covered:

* `word`: contractions, runs of letters, single digits, runs of other signs;
  white space parts them and is dropped.  Text is first composed (NFC) and lowered.
* `byte`: contractions, runs of letters, of digits or of other signs, each with
  one blank before it, and runs of white space.

Character classes come from Python's Unicode tables.  The library's tables
differ only in code points that are unassigned here, so a text with such a
character, or with the string of a special token, is left to the library
(`odd`); everything else is split here.
"""

from __future__ import annotations

import unicodedata
from dataclasses import dataclass

import numpy as np

SPACE, LETTER, DIGIT, OTHER, ODD, BREAK = range(6)
#: The white space of the patterns' \s, beyond 9-13.
SPACES = [0x20, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]
#: Endings that a pattern takes together with the apostrophe before them.
CONTRACTIONS = ("s", "t", "re", "ve", "m", "ll", "d")

_classes: np.ndarray | None = None


def classes() -> np.ndarray:
    """The class of every code point."""
    global _classes
    if _classes is None:
        of = {"L": LETTER, "N": DIGIT}
        t = np.array([ODD if (c := unicodedata.category(chr(i))) == "Cn" else of.get(c[0], OTHER) for i in range(0x110000)], dtype=np.uint8)
        t[9:14] = SPACE
        t[SPACES] = SPACE
        _classes = t
    return _classes


def lowered(text: str) -> str:
    """NFC, then the lower case of each character by itself (a final sigma stays plain)."""
    if text.isascii():
        return text.lower()
    return unicodedata.normalize("NFC", text).replace("Σ", "σ").lower()


@dataclass
class Tokens:
    """Byte spans of the pre-tokens in data; first[d]:first[d+1] are text d's."""

    data: np.ndarray
    start: np.ndarray
    end: np.ndarray
    first: np.ndarray
    odd: np.ndarray


def _contractions(cp: np.ndarray, kind: np.ndarray, free: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(apostrophes that begin a contraction, length of its ending)."""
    n = len(cp)
    at = np.flatnonzero(free & (cp == 39))
    if not len(at):
        return at, at
    pad = np.concatenate([cp, [0, 0]])
    size = np.zeros(len(at), dtype=np.int64)
    for c in CONTRACTIONS:
        hit = pad[at + 1] == ord(c[0])
        if len(c) == 2:
            hit &= pad[np.minimum(at + 2, n + 1)] == ord(c[1])
        size[hit] = len(c)
    return at[size > 0], size[size > 0]


def split(texts: list[str], style: str) -> Tokens:
    """Pre-tokens of each text.  For style `word` texts must have gone through lowered()."""
    n = len(texts)
    joined = "\n".join(texts) + "\n"
    cp = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
    data = np.frombuffer(joined.encode("utf-8"), dtype=np.uint8)
    kind = classes()[cp]
    ends = np.cumsum(np.fromiter((len(t) + 1 for t in texts), dtype=np.int64, count=n)) if n else np.zeros(0, dtype=np.int64)
    begins = ends - np.diff(ends, prepend=0)
    odd_total = np.concatenate([[0], np.cumsum(kind == ODD)])
    odd = odd_total[ends] > odd_total[begins] if n else np.zeros(0, dtype=bool)
    kind[ends - 1] = BREAK
    before = np.concatenate([[BREAK], kind[:-1]]).astype(np.uint8)
    change = kind != before
    if style == "word":
        token = (kind != SPACE) & (kind != BREAK)
        start = token & (change | (kind == DIGIT))
        at, size = _contractions(cp, kind, token & change)
    else:
        token = kind != BREAK
        blank = np.concatenate([[False], (cp[:-1] == 32) & (kind[:-1] == SPACE)])
        solid = (kind != SPACE) & token
        # a run takes one blank before it
        start = solid & change & ~blank
        after = np.concatenate([kind[1:], [BREAK]])
        space = kind == SPACE
        next_solid = (after != SPACE) & (after != BREAK)
        # white space: a run begins a token, and its last character does before something solid
        start |= space & (change | next_solid)
        at, size = _contractions(cp, kind, solid & change & ~blank)
    if len(at):
        start[at + 1] = False
        beyond = at + 1 + size
        start[beyond[kind[beyond] == LETTER]] = True
        # a blank is never attached to what follows a contraction's letters, so nothing else moves
    where = np.flatnonzero(start)
    # a token ends at the next start or the next character outside tokens (the last one always is)
    stops = np.flatnonzero(start | ~token)
    finish = stops[np.flatnonzero(start[stops]) + 1]
    if len(data) != len(cp):
        byte = np.concatenate([np.flatnonzero((data & 0xC0) != 0x80), [len(data)]])
        first = np.searchsorted(where, np.concatenate([begins, [len(cp)]]))
        return Tokens(data, byte[where], byte[finish], first, odd)
    return Tokens(data, where, finish, np.searchsorted(where, np.concatenate([begins, [len(cp)]])), odd)
