"""Settings of a set encoding, and how large one must be for a wanted error."""

from __future__ import annotations

import json
import math
from dataclasses import asdict, dataclass, replace


#: Partitions of space that need no registration (``kernels.register_partition`` adds others).
BUILT_IN = ("sign", "center")


@dataclass(frozen=True)
class EncodeParams:
    """A set encoding: ``reps`` independent partitions of space, each with ``cells`` blocks of ``proj_dim`` numbers.

    ``arithmetic='fixed'`` keeps everything in whole numbers (vectors times 2^20, planes of the ``int12`` law, signs
    without scale, means rounded down), so that any engine gives the same bits.
    """

    dim: int
    hash_bits: int
    proj_dim: int
    reps: int
    seed: int = 42
    partition: str = "sign"
    n_centers: int = 0
    fill: bool = True
    final_dim: int | None = None
    plane_law: str = "gaussian"
    arithmetic: str = "float"
    doc_block: str = "mean"

    def __post_init__(self) -> None:
        if self.partition != "sign" and self.n_centers < 1:
            raise ValueError("a partition other than sign cells needs n_centers")
        if self.plane_law not in ("gaussian", "int12") or self.arithmetic not in ("float", "fixed"):
            raise ValueError("plane_law is gaussian or int12, arithmetic float or fixed")
        if self.arithmetic == "fixed" and self.plane_law != "int12":
            raise ValueError("fixed arithmetic needs the int12 law")
        if self.doc_block not in ("mean", "sum"):
            raise ValueError("doc_block is mean or sum")
        if not 1 <= self.proj_dim <= self.dim or self.reps < 1 or not 0 <= self.hash_bits <= 16:
            raise ValueError("proj_dim lies in 1..dim, reps is at least 1, hash_bits in 0..16")

    @property
    def cells(self) -> int:
        return 1 << self.hash_bits if self.partition == "sign" else self.n_centers

    @property
    def projected(self) -> bool:
        """With as many numbers as dimensions there is no projection at all."""
        return self.proj_dim < self.dim

    @property
    def inner_width(self) -> int:
        return self.cells * self.proj_dim * self.reps

    @property
    def width(self) -> int:
        return self.final_dim or self.inner_width

    def with_(self, **changes: object) -> EncodeParams:
        return replace(self, **changes)

    def to_json(self) -> str:
        return json.dumps(asdict(self), sort_keys=True)

    @staticmethod
    def from_json(text: str) -> EncodeParams:
        return EncodeParams(**json.loads(text))


#: Settings on the quality frontier, by width.
FRONTIER = {1280: (20, 3, 8), 2560: (20, 4, 8), 5120: (20, 5, 8), 10240: (20, 5, 16)}


def frontier(width: int, dim: int, **more: object) -> EncodeParams:
    reps, bits, proj = FRONTIER[width]
    return EncodeParams(dim=dim, hash_bits=bits, proj_dim=proj, reps=reps, **more)


@dataclass(frozen=True)
class Sizes:
    hash_bits: int
    proj_dim: int
    reps: int

    @property
    def width(self) -> int:
        return (1 << self.hash_bits) * self.proj_dim * self.reps


def params_single(eps: float, delta: float, m: int, c1: float = 1.0, c2: float = 1.0) -> Sizes:
    """One pair of sets within additive ``eps`` of the mean similarity with probability 1 - ``delta``; ``m`` vectors in
    all. The constants of the orders of growth are arguments."""
    size = math.log(m / (eps * delta)) / eps**2
    return Sizes(max(1, math.ceil(c1 * size)), max(1, math.ceil(c2 * size)), 1)


def params_search(eps: float, m: int, d: int, n: int, c1: float = 1.0, c2: float = 1.0, c3: float = 1.0) -> Sizes:
    """An ``eps``-approximate nearest set among ``n``, with high probability in ``n``."""
    bits = c1 * math.log(m / eps) / eps**2
    proj = c2 * math.log(m * d * n / eps) / eps**2
    reps = c3 * math.log(n) / eps**2
    return Sizes(max(1, math.ceil(bits)), max(1, math.ceil(proj)), max(1, math.ceil(reps)))


def collision_probability(cosine: float, bits: int) -> float:
    """Chance that two unit vectors share all sign bits."""
    return (1 - math.acos(max(-1.0, min(1.0, cosine))) / math.pi) ** bits
