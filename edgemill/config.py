"""What to generate and how vertices are laid out over owners."""

from __future__ import annotations

from dataclasses import dataclass

#: Customary quadrant probabilities of recursive-matrix generators (fixed values).
SKEWED = (0.57, 0.19, 0.19, 0.05)
UNIFORM = (0.25, 0.25, 0.25, 0.25)


@dataclass(frozen=True)
class GenSpec:
    """A graph of n vertices (2^scale where n is not given) with edge_factor * n edges."""

    scale: int = 10
    edge_factor: int = 16
    probs: tuple[float, float, float, float] = SKEWED
    seed: int = 42
    backend: str = "fast"
    n: int | None = None
    noise: float = 0.0

    def __post_init__(self) -> None:
        if abs(sum(self.probs) - 1) > 1e-9 or min(self.probs) < 0:
            raise ValueError("quadrant probabilities must be non-negative and add up to 1")
        if self.backend not in ("fast", "portable"):
            raise ValueError(f"unknown backend {self.backend!r}")

    @property
    def vertices(self) -> int:
        return self.n if self.n is not None else 1 << self.scale

    @property
    def levels(self) -> int:
        return max(0, (self.vertices - 1).bit_length())

    @property
    def edges(self) -> int:
        return self.vertices * self.edge_factor


@dataclass(frozen=True)
class Layout:
    """n vertices in nb buckets of nc lanes; block and packet sizes of the cost measures."""

    n: int
    nb: int = 4
    nc: int = 2
    block_edges: int = 1024
    chunk_edges: int = 4096
    packet_bytes: int = 16_384

    @property
    def packet_edges(self) -> int:
        return self.packet_bytes // 16

    @staticmethod
    def for_edges(n: int, m: int, bytes_per_bucket: int = 512 << 20) -> Layout:
        """As many buckets as keep one within the given bytes at 16 bytes an edge."""
        return Layout(n, nb=max(1, min(n, -(-m * 16 // bytes_per_bucket))))
