"""Measured units of protocol runs: plan units, bytes a party sends and receives, rounds. Functions of public sizes only.

The constants are textbook costs of three-party replicated sharing on 64-bit words; the shapes are what is compared.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

AND_BYTES = 16  # a word-wide AND: 8 bytes sent and 8 received
ADD, CMP, EQ, MUX = 7, 7, 6, 1  # AND layers
PERMUTE, INTERSECT = 6, 3  # passes over the data of the cited constant-round protocols


def log2(n: float) -> int:
    return max(1, math.ceil(math.log2(max(n, 2))))


def scan_cost(n: int, gates: int, words: int = 1) -> tuple[float, int]:
    return 2 * n * gates * words * AND_BYTES, 2 * log2(n) * gates


def permute_cost(n: int, columns: int) -> tuple[float, int]:
    return PERMUTE * 8 * columns * n, 4


def intersect_cost(n_x: int, n_y: int, columns: int) -> tuple[float, int]:
    return INTERSECT * (16 + 8 * columns) * (n_x + n_y), 6


@dataclass
class Meter:
    """Collects what each step costs. `units` are (attributes + ranks) times rows, as plans are compared by."""

    rows: list[tuple[str, int, float, int]] = field(default_factory=list)  # step, units, bytes, rounds

    def add(self, step: str, units: int, *parts: tuple[float, int]) -> None:
        self.rows.append((step, units, sum(p[0] for p in parts), sum(p[1] for p in parts)))

    @property
    def units(self) -> int:
        return sum(r[1] for r in self.rows)

    @property
    def bytes(self) -> float:
        return sum(r[2] for r in self.rows)

    @property
    def rounds(self) -> int:
        return sum(r[3] for r in self.rows)

    def longest(self, plan) -> int:
        """Rounds when steps of different branches run side by side: the steps of a plan in order, each after those that made
        its inputs."""
        done: dict[str, int] = {}
        for (_, _, _, rounds), s in zip(self.rows, plan.steps):
            start = max(done.get(s.relation, 0), done.get(s.other, 0))
            done[s.relation] = start + rounds
        return max(done.values(), default=0)

    def refresh(self, n: int, keys: int) -> list[tuple[float, int]]:
        return [permute_cost(n, 3 * keys), scan_cost(n, ADD, keys), permute_cost(n, keys)]

    def select(self, n: int, width: int, keys: int) -> None:
        self.add("select", n * width, (n * CMP * AND_BYTES, CMP), *self.refresh(n, keys))

    def aggregate(self, n: int, width: int, keys: int, key_words: int) -> None:
        self.add("aggregate", n * width, permute_cost(n, width + 1), scan_cost(n, EQ * max(key_words, 1) + ADD + MUX), *self.refresh(n, keys))

    def semijoin(self, n_r: int, n_s: int, width: int, keys: int, payload: int = 0) -> None:
        self.add("semijoin" if not payload else "absorb", n_r * width, permute_cost(n_r, width), scan_cost(n_s, EQ), scan_cost(n_r, EQ + ADD), intersect_cost(n_r, n_s, payload + 1),
                 scan_cost(n_r, EQ + MUX, payload + 1), *self.refresh(n_r, keys))

    def expand(self, n: int, m: int, width: int, keys: int) -> None:
        self.add("expand", (n + m) * width, permute_cost(n, 2 * keys), scan_cost(n, ADD, keys + 1), permute_cost(n + m, width + 2), scan_cost(m, MUX, width + 2))

    def join(self, n_r: int, n_s: int, m: int, w_r: int, w_s: int, k_r: int, k_s: int) -> None:
        degree = [scan_cost(n_r, EQ + ADD), scan_cost(n_s, EQ + ADD), intersect_cost(n_r, n_s, 1), intersect_cost(n_s, n_r, 1), scan_cost(n_r, EQ + MUX), scan_cost(n_s, EQ + MUX)]
        grow = [c for n, w, k in ((n_r, w_r, k_r), (n_s, w_s, k_s)) for c in (permute_cost(n, w), scan_cost(n, ADD, k + 1), permute_cost(n + m, w + 2), scan_cost(m, MUX, w + 2))]
        self.add("join", m * (w_r + w_s), *degree, *grow, permute_cost(m, w_s), (2 * m * ADD * AND_BYTES, 2 * ADD))


def sort_merge_join(n_r: int, n_s: int, m: int, words: int, bitonic: bool = False, charge_sort: bool = True) -> tuple[float, int]:
    """Bytes and rounds of a two-way sort-merge join: merge-sort the union, degrees, expansion, and a sort to align."""
    def sort(n: int) -> tuple[float, int]:
        p = log2(n)
        steps = n * p * (p + 1) / 4 if bitonic else n * p
        return steps * (CMP + 2 * MUX * words) * AND_BYTES, (p * (p + 1) // 2 if bitonic else p) * CMP

    n = n_r + n_s
    parts = [*([sort(n)] if charge_sort else []), scan_cost(n, EQ + ADD), scan_cost(n, EQ + ADD), permute_cost(n + m, words), permute_cost(n + m, words), scan_cost(m, MUX, 2 * words), sort(m)]
    return sum(p[0] for p in parts), sum(p[1] for p in parts)


def two_party(n: int, m: int, words: int, relations: int) -> float:
    """Bytes of the two-party system: reduce phase with permutation networks of n log n switches, joins at the receiver."""
    return relations * (n * log2(n) * words * AND_BYTES / 2 + n * words * 3 * AND_BYTES) + m * words * 8


def circuit_three_phase(n: int, m: int) -> float:
    return (n + m) * math.log2(max(n + m, 2)) ** 4


def nested_loop(sizes: list[int], gates: int = EQ) -> float:
    return math.prod(sizes) * gates * AND_BYTES


def plaintext(sizes: list[tuple[int, int]], m: int, out_words: int) -> float:
    """Input plus output size: 8 bytes for each word."""
    return 8 * (sum(n * w for n, w in sizes) + m * out_words)


def amortised_ranks(n: int, m: int, width: int, queries: int) -> float:
    """Units per query if servers sort the shared data once to make the ranks."""
    return n * log2(n) * width / max(queries, 1) + (n + m) * width


def stage_totals(spark) -> tuple[int, int, int]:
    """Stages that have run in this session, the bytes they shuffled and those they spilled."""
    stages = spark.sparkContext._jsc.sc().statusStore().stageList(None, False, False, spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0), None)
    listed = [stages.apply(i) for i in range(stages.size())]
    return len(listed), sum(s.shuffleWriteBytes() for s in listed), sum(s.diskBytesSpilled() for s in listed)
