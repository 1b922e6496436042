"""Parameters of a function, and the hash family that they draw."""

from __future__ import annotations

from dataclasses import asdict, dataclass, field

import numpy as np

from densekeys.functions.encode import MAX_BYTES
from densekeys.functions.hashing import ChunkTables, LinearHash, MixedValues, MixingHash, TabulatedValues
from densekeys.functions.rank import theory_steps

HASHES = ("linear", "mix96", "xx128", "universal")


@dataclass(frozen=True)
class Params:
    """hash: linear (proved), mix96 or xx128 (heuristic), universal (tabulated values, for whole sets); kind: phf (range 2 tau) or mphf (range n); layout: compressed or plain;
    kappa: step of the rank directory, or "theory" for log2(tau) / eps_rank; sigma: bits of a chunk of the linear family's tables."""

    hash: str = "linear"
    kind: str = "mphf"
    layout: str = "compressed"
    eps: float = 0.045
    kappa: int | str = 128
    eps_rank: float = 0.1
    sigma: int = 8
    ell: int = 256
    chunks: int = 6
    max_bytes: int = MAX_BYTES
    popcount_bits: int | str = "native"
    master_seed: int = 20250101
    max_tries: int = 200
    max_restarts: int = 8
    super_keys: int = 1 << 18
    gamma: int = 128

    def __post_init__(self):
        if self.hash not in HASHES or self.kind not in ("phf", "mphf") or self.layout not in ("compressed", "plain"):
            raise ValueError(f"unknown variant {self.hash}, {self.kind}, {self.layout}")
        if self.eps <= 0 or self.eps_rank <= 0 or self.kappa != "theory" and (self.kappa % 8 or self.kappa <= 0):
            raise ValueError("eps must be positive, and kappa a positive multiple of 8 or 'theory'")

    def steps(self, tau: np.ndarray) -> int | np.ndarray:
        """Places between entries of the rank directory."""
        return theory_steps(tau, self.eps_rank) if self.kappa == "theory" else self.kappa

    @property
    def seeds_per_bucket(self) -> int:
        return 2 if self.hash == "mix96" else 1

    @property
    def native(self) -> bool:
        """Whether fingerprints are the engine's own hashes."""
        return self.hash in ("xx128", "universal")

    @property
    def fingerprint_bytes(self) -> int:
        return 12 if self.hash == "mix96" else 16


@dataclass
class Family:
    """The drawn tables of one attempt; small, and rebuilt from the seed on every executor."""

    params: Params
    attempt: int = 0
    fingerprint: object = field(init=False)
    values: object = field(init=False)

    def __post_init__(self):
        seed = (self.params.master_seed * 31 + self.attempt) & 0xFFFFFF
        p = self.params
        self.fingerprint = LinearHash(seed, p.max_bytes, sigma=p.sigma) if p.hash == "linear" else MixingHash(seed)
        self.values = ChunkTables(seed, p.chunks) if p.hash == "linear" else TabulatedValues(seed) if p.hash == "universal" else MixedValues()

    @property
    def fixed_bytes(self) -> int:
        return self.fingerprint.table_bytes + self.values.table_bytes


_families: dict[tuple, Family] = {}


def family(params: Params, attempt: int) -> Family:
    """One Family for each worker and attempt."""
    key = (tuple(sorted((k, str(v)) for k, v in asdict(params).items())), attempt)
    if key not in _families:
        _families.clear()
        _families[key] = Family(params, attempt)
    return _families[key]
