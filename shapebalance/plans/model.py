"""The small frozen records that plans carry beside DataFrames."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Bounds:
    """Upper bounds of a batch: m_mem tokens (B * S) and m_comp load units (B * S^p)."""

    m_mem: float = 144_000.0
    m_comp: float = 2_400_000_001.5
    p: float = 2.0

    def __post_init__(self):
        if self.m_mem <= 0 or self.m_comp <= 0 or self.p <= 0:
            raise ValueError("bounds and exponent must be positive")


@dataclass(frozen=True)
class CostModel:
    """Step time a + b * B * (S / s_ref)^p, with the fit's r2 over n cells."""

    a: float = 1.0
    b: float = 2e-9
    p: float = 2.0
    s_ref: float = 1.0
    r2: float = 1.0
    n: int = 0


#: Arms of the experiments: equal-token batching and dual-constraint batching.
ARMS = ("equal_token", "dual")
SEED = 42
