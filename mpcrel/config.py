"""Fixed assumptions of the model and tunables of the engine."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class MpcConf:
    """parties, adversary and bit lengths are those of the model; other values are refused."""

    parties: int = 3
    adversary: str = "semi-honest"
    word_bits: int = 64
    kappa: int = 128  # computational security parameter
    sigma: int = 40  # statistical security parameter
    chunk: int = 1 << 16  # rows that one window of a scan holds; public
    broadcast_chunks: int = 100_000  # chunk summaries up to this number are broadcast
    broadcast_rows: int = 200_000  # a relation of up to this public size is broadcast to its partners
    word_places: int = 1 << 28  # places of which one bit each, and a count per 64, are broadcast
    sort_rows: int = 1 << 18  # rows of a block of a full sort, beyond 32 blocks
    explode_block: int = 1 << 16  # copies that one row gives in one step of an expansion

    def __post_init__(self):
        if self.parties != 3 or self.adversary != "semi-honest":
            raise ValueError("three parties, of which one may be corrupted and follows the protocol")


DEFAULT = MpcConf()
