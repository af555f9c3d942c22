"""Public configuration of a snapshot."""

from __future__ import annotations

from dataclasses import dataclass


def is_power_of_two(x: int) -> bool:
    return x > 0 and x & (x - 1) == 0


def next_power_of_two(x: int) -> int:
    return 1 << max(0, (x - 1).bit_length())


@dataclass(frozen=True)
class Config:
    """dims D, lists n_list, probes n_probe, slots a list n, blocks M, codes K, answers k; scale is 2^bits - 1."""

    dims: int
    n_list: int
    n_probe: int
    slots: int
    blocks: int
    codes: int
    k: int
    scale_bits: int = 16
    pipeline: str = "zk"

    @property
    def capacity(self) -> int:
        return self.n_list * self.slots

    @property
    def scanned(self) -> int:
        return self.n_probe * self.slots

    @property
    def code_bits(self) -> int:
        return self.blocks * (self.codes.bit_length() - 1)

    @property
    def ratio(self) -> float:
        return self.n_probe / self.n_list

    @property
    def width(self) -> int:
        return self.dims // self.blocks

    @property
    def scale(self) -> int:
        return (1 << self.scale_bits) - 1

    @property
    def d_max(self) -> int:
        """Above the distance of any slot in use: a coordinate difference is at most 4 * scale."""
        return 16 * self.dims * self.scale**2 + 1

    def validate(self, n0: int | None = None) -> Config:
        if self.dims % self.blocks:
            raise ValueError(f"{self.dims} dimensions do not split into {self.blocks} blocks")
        if not is_power_of_two(self.codes):
            raise ValueError("the number of codewords must be a power of two")
        if not 1 <= self.n_probe <= self.n_list:
            raise ValueError("probes must be between 1 and the number of lists")
        if not 1 <= self.k <= self.scanned:
            raise ValueError("k must be between 1 and the number of scanned slots")
        if n0 is not None and self.capacity < n0:
            raise ValueError(f"{n0} vectors do not fit into {self.n_list} lists of {self.slots}")
        if self.d_max >= 1 << 59:
            raise ValueError("distances leave the range that comparisons cover")
        return self

    def canonical(self, v_max: float) -> str:
        """All public parameters as one text, which a version's digest binds."""
        return "|".join(map(str, ["config", self.dims, self.n_list, self.n_probe, self.slots, self.blocks, self.codes, self.k, self.scale_bits, repr(v_max), self.d_max, self.pipeline]))
