"""Three-way XOR sharing of 64-bit words and gates on shared words, as columns of plain frames.

A shared column c is a struct (s0, s1, s2) whose XOR is the value; party i may read s_i and s_(i+1). All parties live in one
cluster here: the gates are exact and their costs are those of the protocol, but nothing is hidden from the cluster. Randomness
is a pure function of (nonce, gate, row, word), so that a task that runs again draws the same words.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import POS, settle


def prg(nonce: str, stream: str, row: Column, strong: bool = True) -> Column:
    """A pseudo-random word; the fast form is for tests only."""
    seed = F.concat_ws("|", F.lit(nonce), F.lit(stream), row.cast("string"))
    if not strong:
        return F.xxhash64(seed)
    return F.conv(F.substring(F.sha2(seed, 256), 1, 16), 16, -10).cast("long")


def share(df: DataFrame, cols: list[str], nonce: str, row: str = POS, strong: bool = True) -> DataFrame:
    out = {}
    for c in cols:
        a, b = prg(nonce, f"{c}/0", F.col(row), strong), prg(nonce, f"{c}/1", F.col(row), strong)
        out[c] = F.struct(a.alias("s0"), b.alias("s1"), F.col(c).cast("long").bitwiseXOR(a).bitwiseXOR(b).alias("s2"))
    return df.withColumns(out)


def party_view(df: DataFrame, cols: list[str], party: int) -> DataFrame:
    """What one party holds of the shared columns."""
    i, j = party, (party + 1) % 3
    return df.withColumns({c: F.struct(F.col(f"{c}.s{i}").alias(f"s{i}"), F.col(f"{c}.s{j}").alias(f"s{j}")) for c in cols})


def open_shares(df: DataFrame, cols: list[str]) -> DataFrame:
    return df.withColumns({c: F.col(f"{c}.s0").bitwiseXOR(F.col(f"{c}.s1")).bitwiseXOR(F.col(f"{c}.s2")) for c in cols})


def open_views(views: dict[int, DataFrame], cols: list[str], row: str = POS) -> DataFrame:
    """Values from the views of any two parties, joined by row."""
    (i, a), (j, b) = sorted(views.items())
    other = b.select(F.col(row).alias("__row"), *(F.col(c).alias(f"__o_{c}") for c in cols))
    both = a.join(other, F.col(row) == F.col("__row"))
    held = lambda c, k: F.col(f"{c}.s{k}") if k in (i, (i + 1) % 3) else F.col(f"__o_{c}.s{k}")
    return both.withColumns({c: held(c, 0).bitwiseXOR(held(c, 1)).bitwiseXOR(held(c, 2)) for c in cols}).drop("__row", *(f"__o_{c}" for c in cols))


def zero_words(nonce: str, stream: str, row: Column, strong: bool = True) -> list[Column]:
    """Three words that XOR to zero, each from two pairwise keys."""
    r = [prg(nonce, f"{stream}/{k}", row, strong) for k in range(3)]
    return [r[k].bitwiseXOR(r[(k + 1) % 3]) for k in range(3)]


def refresh_shares(df: DataFrame, cols: list[str], nonce: str, row: str = POS, strong: bool = True) -> DataFrame:
    out = {}
    for c in cols:
        z = zero_words(nonce, f"refresh/{c}", F.col(row), strong)
        out[c] = F.struct(*(F.col(f"{c}.s{k}").bitwiseXOR(z[k]).alias(f"s{k}") for k in range(3)))
    return df.withColumns(out)


class Circuit:
    """Gates over the shared columns of a frame. Each gate adds one column; `ands` and `depth` count what would be sent."""

    def __init__(self, df: DataFrame, nonce: str, row: str = POS, strong: bool = False):
        self.df, self.nonce, self.row, self.strong, self.count, self.ands = df, nonce, row, strong, 0, 0

    def _put(self, words: list[Column]) -> str:
        self.count += 1
        name = f"__w{self.count}"
        self.df = self.df.withColumn(name, F.struct(*(w.alias(f"s{k}") for k, w in enumerate(words))))
        return name

    @staticmethod
    def _words(name: str) -> list[Column]:
        return [F.col(f"{name}.s{k}") for k in range(3)]

    def constant(self, value: int) -> str:
        return self._put([F.lit(value).cast("long"), F.lit(0).cast("long"), F.lit(0).cast("long")])

    def xor_(self, a: str, b: str) -> str:
        return self._put([x.bitwiseXOR(y) for x, y in zip(self._words(a), self._words(b))])

    def not_(self, a: str) -> str:
        x = self._words(a)
        return self._put([x[0].bitwiseXOR(F.lit(-1)), x[1], x[2]])

    def and_(self, a: str, b: str) -> str:
        x, y = self._words(a), self._words(b)
        self.ands += 1
        z = zero_words(self.nonce, f"and{self.ands}", F.col(self.row), self.strong)
        cross = [x[k].bitwiseAND(y[k]).bitwiseXOR(x[k].bitwiseAND(y[(k + 1) % 3])).bitwiseXOR(x[(k + 1) % 3].bitwiseAND(y[k])).bitwiseXOR(z[k]) for k in range(3)]
        return self._put(cross)

    def or_(self, a: str, b: str) -> str:
        return self.xor_(self.xor_(a, b), self.and_(a, b))

    def left(self, a: str, n: int) -> str:
        return self._put([F.shiftleft(w, n) for w in self._words(a)])

    def right(self, a: str, n: int) -> str:
        return self._put([F.shiftrightunsigned(w, n) for w in self._words(a)])

    def mask(self, bit: str) -> str:
        """All 64 bits equal to the lowest bit; local, since it is linear over XOR."""
        return self._put([F.shiftright(F.shiftleft(w, 63), 63) for w in self._words(bit)])

    def add(self, a: str, b: str, carry: bool = False) -> str:
        """Sum modulo 2^64 by a parallel-prefix carry circuit; with `carry`, plus one."""
        p = half = self.xor_(a, b)
        g = self.and_(a, b)
        if carry:  # the carry into bit 0 acts through bit 0's propagate
            g = self.xor_(g, self.and_(p, self.constant(1)))
        for k in (1, 2, 4, 8, 16, 32):
            g, p = self.xor_(g, self.and_(p, self.left(g, k))), self.and_(p, self.left(p, k))
        out = self.xor_(half, self.left(g, 1))
        return self.xor_(out, self.constant(1)) if carry else out

    def sub(self, a: str, b: str) -> str:
        return self.add(a, self.not_(b), carry=True)

    def lt(self, a: str, b: str) -> str:
        """Lowest bit: a < b, signed."""
        d = self.sub(a, b)
        overflow = self.and_(self.xor_(a, b), self.xor_(d, a))
        return self.right(self.xor_(d, overflow), 63)

    def le(self, a: str, b: str) -> str:
        """Lowest bit: a <= b, signed."""
        return self.xor_(self.lt(b, a), self.constant(1))

    def eq(self, a: str, b: str) -> str:
        """Lowest bit: a = b."""
        x = self.xor_(a, b)
        for k in (32, 16, 8, 4, 2, 1):
            x = self.or_(x, self.right(x, k))
        one = self.constant(1)
        return self.xor_(self.and_(x, one), one)

    def mux(self, bit: str, a: str, b: str) -> str:
        """a where the bit is set, else b."""
        return self.xor_(b, self.and_(self.mask(bit), self.xor_(a, b)))

    def mul(self, a: str, b: str, bits: int = 64) -> str:
        """Product modulo 2^64 of a and the lowest `bits` bits of b, by shifted additions; lineage is cut between them."""
        total = None
        for k in range(bits):
            part = self.and_(self.mask(self.right(b, k)), self.left(a, k))
            total = part if total is None else self.add(total, part)
            self.df = settle(self.df.drop(*(c for c in self.df.columns if c.startswith("__w") and c not in (total, a, b))))
        return total


def network(n: int) -> list[tuple[int, int]]:
    """Stages (size, distance) of the bitonic network for n places, n a power of two."""
    stages, size = [], 2
    while size <= n:
        distance = size // 2
        while distance:
            stages.append((size, distance))
            distance //= 2
        size *= 2
    return stages


def sort_network(df: DataFrame, key: str, payload: list[str], n: int, nonce: str) -> tuple[DataFrame, int]:
    """Rows in ascending order of a key of distinct positive words, sorted on shares by a bitonic network, and its comparators.

    Places beyond the n rows hold the largest word and are cut off. Every stage compares each place with its partner by a
    circuit and takes one of the two rows by multiplexers, whatever the words are; only the result is opened.
    """
    places = 1 << max(1, (n - 1).bit_length())
    kinds = [key, *payload]
    extra = df.sparkSession.range(n + 1, places + 1).select(F.col("id").alias(POS), F.lit((1 << 62)).alias(key), *(F.lit(0).cast("long").alias(c) for c in payload))
    held = settle(share(df.select(POS, *kinds).unionByName(extra), kinds, nonce, POS, False))
    at, comparators = F.col(POS) - 1, 0
    for turn, (size, distance) in enumerate(network(places)):
        partner = held.select((at.bitwiseXOR(F.lit(distance)) + 1).alias(POS), *(F.col(c).alias(f"other_{c}") for c in kinds))
        c = Circuit(held.join(partner, POS), f"{nonce}/{turn}")
        # the smaller row goes to the lower place in ascending runs and to the higher one in descending runs; that is public
        low = (at.bitwiseAND(F.lit(distance)) == 0) == (at.bitwiseAND(F.lit(size)) == 0)
        swap = F.when(low, 0).otherwise(1).cast("long")
        public = c._put([swap, F.lit(0).cast("long"), F.lit(0).cast("long")])
        takes = c.xor_(c.lt(key, f"other_{key}"), public)
        made = {k: c.mux(takes, k, f"other_{k}") for k in kinds}
        held = settle(c.df.select(POS, *(F.col(w).alias(k) for k, w in made.items())))
        comparators += places // 2
    return open_shares(held, kinds).where(F.col(POS) <= n), comparators
