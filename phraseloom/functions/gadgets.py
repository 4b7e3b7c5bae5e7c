"""Strings that turn orthogonality of Boolean vectors into parse lengths.

Symbols are code points: three per coordinate (zero, one, padding), and fresh separators, each used once.
"""

from __future__ import annotations

from math import isqrt

FIRST = 0x100
#: Separators start here: above everything that coordinates use, and above the surrogates.
SEPARATORS = 0x10000


def symbol(value: int, j: int) -> str:
    """value 0, 1, or 2 (padding) of coordinate j (1-based)."""
    return chr(FIRST + 3 * j + value)


class Fresh:
    def __init__(self, used: int = 0) -> None:
        self.next = SEPARATORS + used

    def __call__(self) -> str:
        self.next += 1
        return chr(self.next - 1)


def simple_dictionary(d: int, fresh: Fresh) -> str:
    out = []
    for j in range(1, d + 1):
        out += [symbol(0, j) * 2, fresh()]
        for x in (0, 1):
            for y in (0, 1):
                out += [symbol(x, j), symbol(y, j + 1), fresh()]
    return "".join(out)


def simple_query(u: list[int], fresh: Fresh) -> str:
    return "".join(symbol(1 - bit, j) * 2 + fresh() for j, bit in enumerate(u, 1))


def simple_vector(v: list[int]) -> str:
    return "".join(symbol(bit, j) * 2 for j, bit in enumerate(v, 1))


def dictionary(n: int, d: int, fresh: Fresh) -> str:
    root = isqrt(n)
    skips = [symbol(0, j) * (4 * root) + symbol(2, j) * root + fresh() for j in range(1, d + 1)]
    halves = [
        symbol(x, j) * (2 * root) + symbol(2, j) * pad + symbol(y, j + 1) * (2 * root) + fresh()
        for j in range(1, d + 1) for pad in range(root + 1) for x in (0, 1) for y in (0, 1)
    ]
    return "".join(skips + halves)


def vector(v: list[int], i: int, n: int) -> str:
    """Vector number i (1-based) of n: the i-th pair of repeat counts keeps it from copying its predecessors."""
    high, low = divmod(i, isqrt(n))
    return "".join(symbol(bit, j) * (3 * isqrt(n) + high) + symbol(2, j) * low for j, bit in enumerate(v, 1))


def query_vector(u: list[int], n: int, fresh: Fresh) -> str:
    """Every coordinate has the same length; a set bit breaks the run of ones by a separator, one substitution."""
    root = isqrt(n)
    out = []
    for j, bit in enumerate(u, 1):
        middle = fresh()
        out.append(symbol(1, j) * (2 * root) + (middle if bit else symbol(1, j)) + symbol(1, j) * (2 * root) + symbol(2, j) * root + fresh())
    return "".join(out)


def matrix(vectors: list[list[int]], fresh: Fresh) -> list[str]:
    """Each vector's block with its separator."""
    return [vector(v, i, len(vectors)) + fresh() for i, v in enumerate(vectors, 1)]
