"""Character classes as a tokenizer's own library sees them.

Two regular-expression engines may know different versions of Unicode. The classes are
therefore asked from the library, for the characters below TOP; a text with any other
character, or with one that Python would normalise differently, goes through the library.
"""

from __future__ import annotations

import re
from collections.abc import Callable

TOP = 0x3000


def as_ranges(codes: list[int]) -> str:
    """Code points as ranges of a character class."""
    inside = set(codes)
    starts = [c for c in codes if c - 1 not in inside]
    ends = [c for c in codes if c + 1 not in inside]
    return "".join(f"\\u{a:04x}-\\u{b:04x}" for a, b in zip(starts, ends))


def probe(pieces: Callable[[str], list[tuple[int, int]]]) -> tuple[str, str, str]:
    """(letters, numbers, spaces) below TOP, from the pieces that a pre-tokenizer cuts."""
    letters, numbers, spaces = [], [], []
    for code in range(TOP):
        c = chr(code)
        if pieces("a" + c) == [(0, 2)]:
            letters.append(code)
        elif pieces("!" + c) != [(0, 2)]:
            # a number joins a number, or stands alone where numbers are cut one by one
            alone = pieces(c + c) == [(0, 1), (1, 2)]
            (numbers if pieces("1" + c) == [(0, 2)] or alone else spaces).append(code)
    return as_ranges(letters), as_ranges(numbers), as_ranges(spaces)


def outside(odd: list[int]) -> Callable[[str], object]:
    """Search for a character at or above TOP, or for an odd one."""
    return re.compile(f"[{as_ranges(odd)}]|[^\\u0000-\\u{TOP - 1:04x}]" if odd else f"[^\\u0000-\\u{TOP - 1:04x}]").search
