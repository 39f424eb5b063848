"""Hashed words and character n-grams of many texts at once, in numpy.

Texts are laid side by side as code points, in parts of bounded size. The hash of a stretch of characters is a polynomial in
them modulo 2^64, read off prefix sums, so that no word is looked at one by one and nothing needs to be remembered.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import lru_cache

#: Characters that are hashed together. A longer text is cut after white space where there is some within a part.
PART = 1 << 17
#: Odd base of the polynomial, and its inverse modulo 2^64.
_BASE = 0xD1342543DE82EF95
_INVERSE = pow(_BASE, -1, 1 << 64)


def odd(n: int, seed: int) -> list[int]:
    """n odd multipliers of 64 bits."""
    import numpy as np

    return [int(x) | 1 for x in np.random.default_rng(seed).integers(1 << 62, 1 << 63, n, dtype="uint64") * np.uint64(2)]


@lru_cache(maxsize=4)
def character_table(kind: str):
    """Whether each code point is of the kind: `solid` (no white space) or `word` (a letter or a digit)."""
    import sys

    import numpy as np

    test: Callable[[str], bool] = {"solid": lambda c: not c.isspace(), "word": str.isalnum}[kind]
    return np.fromiter((test(chr(c)) for c in range(sys.maxunicode + 1)), bool, sys.maxunicode + 1)


@lru_cache(maxsize=1)
def _powers():
    import numpy as np

    up, down = (np.cumprod(np.concatenate([np.ones(1, "uint64"), np.full(PART + 1, b, "uint64")])) for b in (_BASE, _INVERSE))
    return up, down


def code_points(text: str):
    import numpy as np

    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4")


def _cut(text: str) -> Iterator[str]:
    at = 0
    while len(text) - at > PART:
        end = at + PART
        space = max(text.rfind(c, at + PART // 2, end) for c in " \n\t")
        end = end if space < 0 else space + 1
        yield text[at:end]
        at = end
    yield text[at:]


def parts(texts: list) -> Iterator[tuple]:
    """(code points, owner of each place): whole short texts together, long texts in several parts; a space after each."""
    import numpy as np

    held, owners, size = [], [], 0

    def laid():
        return code_points(" ".join([*held, ""])), np.repeat(owners, [len(h) + 1 for h in held])

    for i, text in enumerate(texts):
        for part in _cut(text or ""):
            if held and size + len(part) + 1 > PART:
                yield laid()
                held, owners, size = [], [], 0
            held.append(part)
            owners.append(i)
            size += len(part) + 1
    if held:
        yield laid()


def runs(inside):
    """Starts and ends of the maximal runs of true values."""
    import numpy as np

    change = np.diff(np.concatenate([[0], inside.view("int8"), [0]]))
    return np.flatnonzero(change == 1), np.flatnonzero(change == -1)


class Stretches:
    """Hashes of stretches of a part."""

    def __init__(self, codes):
        import numpy as np

        up, self.down = _powers()
        self.sums = np.concatenate([np.zeros(1, "uint64"), np.cumsum((codes.astype("uint64") + np.uint64(1)) * up[: len(codes)])])

    def hashes(self, starts, ends):
        import numpy as np

        h = (self.sums[ends] - self.sums[starts]) * self.down[starts]
        return (h ^ (h >> np.uint64(32))) * np.uint64(0x9E3779B97F4A7C15)


def bucket(h, bits: int):
    """The leading bits, which a multiplication by an odd number mixes best."""
    import numpy as np

    return (h >> np.uint64(64 - bits)).astype("int64")


def n_grams(codes, starts, ends, sizes: range, multipliers: list[int], bits: int) -> Iterator[tuple]:
    """For each size, (number of the run, bucket) of the n-grams of every run, between a mark of its start and one of its end."""
    import numpy as np

    lengths = ends - starts
    total = int(lengths.sum()) + 2 * len(starts)
    whose = np.repeat(np.arange(len(starts)), lengths + 2)
    marked = np.empty(total, "uint64")
    first = np.cumsum(lengths + 2) - (lengths + 2)
    inner = np.ones(total, bool)
    inner[first] = inner[first + lengths + 1] = False
    marked[first], marked[first + lengths + 1] = ord("<"), ord(">")
    solid = np.zeros(len(codes) + 1, "int8")
    solid[starts] = 1
    solid[ends] -= 1
    marked[inner] = codes[np.cumsum(solid[:-1], dtype="int8").view(bool)]
    marked += np.uint64(1)
    for k in sizes:
        n = total - k + 1
        if n < 1:
            continue
        h = np.full(n, k, "uint64")
        for place in range(k):
            h += marked[place : place + n] * np.uint64(multipliers[place])
        fits = whose[:n] == whose[k - 1 :]
        h = h[fits]
        yield whose[:n][fits], bucket((h ^ (h >> np.uint64(29))) * np.uint64(multipliers[-1]), bits)
