"""Published sizes and frequencies of nine fragments, to check uniform loads and benefits against."""

from __future__ import annotations

from loadshard.operators.fragments import Fragment

#: Fixed values.
SIZES = (2000, 4999, 3000, 3000, 2000, 1700, 300, 1, 3000)
FREQUENCIES = (11, 2, 3, 1, 1, 1, 3, 10, 0)


def table() -> list[Fragment]:
    return [Fragment(i + 1, i, (), (), s, f, i == 8) for i, (s, f) in enumerate(zip(SIZES, FREQUENCIES, strict=True))]
