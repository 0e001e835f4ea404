"""Sizes of sketches: from error targets, from bytes, from a stream's length; page geometry and buffers."""

from __future__ import annotations

import hashlib
import math
from dataclasses import asdict, dataclass, replace

CELL_BYTES = 8
BLOCK_BYTES = 4096
#: Ranges from here need 64-bit hashes.
WIDE = 1 << 24


def _depth(delta: float, rounding: str) -> float:
    depth = math.log(1 / delta)
    return math.ceil(depth) if rounding == "ceil" else depth


def family_over(family: str, size: int) -> str:
    """The hash family over [0, size): 'auto' stands for the 32-bit one as long as it is not biased there."""
    return ("xx64" if size >= WIDE else "murmur32") if family == "auto" else family


@dataclass(frozen=True)
class SketchConfig:
    """Parameters of a sketch: permitted error eps (a share of n), failure probability, depth rows and width columns.

    family 'auto' is chosen by the range that is hashed to: the width for flat rows, the pages and their columns for pages. 'portable' is
    the 32-bit hash over any range, for results that another engine must find too; over 2^24 places and more their shares of the keys
    differ by up to places/2^32.
    """

    eps: float
    delta: float
    depth: int
    width: int
    n: int = 0
    cell_bytes: int = CELL_BYTES
    family: str = "murmur32"
    seed_base: int = 0

    def __post_init__(self) -> None:
        if not 0 < self.delta < 1 or not 0 < self.eps < 1:
            raise ValueError("eps and delta must lie between 0 and 1")
        if self.depth < 1 or self.width < 1 or self.cell_bytes < 1:
            raise ValueError("depth, width and cell_bytes must be positive")
        if self.family not in ("murmur32", "xx64", "affine", "auto", "portable"):
            raise ValueError(f"unknown hash family {self.family}")
        if self.family == "murmur32" and self.width >= WIDE:
            raise ValueError("widths from 2^24 need family xx64: 32-bit hashes are biased there")

    @classmethod
    def from_error(cls, eps: float, delta: float, n: int = 0, **more) -> SketchConfig:
        width = math.ceil(math.e / eps)
        more.setdefault("family", "auto" if width >= WIDE else "murmur32")
        return cls(eps, delta, _depth(delta, "ceil"), width, n, **more)

    @classmethod
    def from_stream(cls, n: int, overestimate: float = 8, delta: float = 0.01, **more) -> SketchConfig:
        """A fixed absolute overestimate over n weights: the size grows with n."""
        return cls.from_error(overestimate / max(n, overestimate + 1), delta, n=n, **more)

    @classmethod
    def from_size(cls, size_bytes: int, delta: float, overestimate: float, cell_bytes: int = CELL_BYTES, **more) -> SketchConfig:
        """What a number of bytes holds: columns, and the n at which the overestimate is reached."""
        cells, depth = size_bytes / cell_bytes, math.ceil(math.log(1 / delta))
        n = math.floor(cells * overestimate / (depth * math.e))
        width = math.ceil(cells / depth)
        more.setdefault("family", "auto" if width >= WIDE else "murmur32")
        return cls(overestimate / n, delta, depth, width, n, cell_bytes, **more)

    @classmethod
    def from_policy(cls, n: int, policy: str, delta: float = 0.01, **more) -> SketchConfig:
        """Permitted errors that grow slower than n: n/log n, sqrt(n), n^(3/4), or the constant 8."""
        errors = {"n_over_log_n": n / math.log(n), "sqrt_n": math.sqrt(n), "n_pow_3_4": n**0.75, "constant": 8.0}
        return cls.from_error(errors[policy] / n, delta, n=n, **more)

    @property
    def flat_family(self) -> str:
        return family_over(self.family, self.width)

    @property
    def size_bytes(self) -> int:
        return self.depth * self.width * self.cell_bytes

    @property
    def effective_eps(self) -> float:
        return math.e / self.width

    def oversubscription(self, ram_bytes: int) -> float:
        return self.size_bytes / ram_bytes

    def fingerprint(self) -> str:
        """Equal only for sketches that can be merged and asked together."""
        return hashlib.md5(repr(sorted(asdict(self).items())).encode()).hexdigest()

    def with_(self, **changes) -> SketchConfig:
        return replace(self, **changes)


def size_formula(eps: float, delta: float, cell_bytes: int = 4) -> float:
    """Bytes of a sketch with unrounded depth and width."""
    return math.log(1 / delta) * (math.e / eps) * cell_bytes


@dataclass(frozen=True)
class PageGeometry:
    """How a sketch is cut into pages.

    aligned: every page has floor(B/r) columns and never crosses a block. straddling: page p has the columns from floor(p*B/r) to
    floor((p+1)*B/r), and may touch two blocks.
    """

    cfg: SketchConfig
    block_bytes: int = BLOCK_BYTES
    mode: str = "aligned"
    pages: int = 0

    @classmethod
    def of(cls, cfg: SketchConfig, block_bytes: int = BLOCK_BYTES, mode: str = "aligned") -> PageGeometry:
        cells = block_bytes // cfg.cell_bytes
        if cells < cfg.depth:
            raise ValueError("a page must hold at least one column")
        if mode == "aligned":
            pages = math.ceil(cfg.width / (cells // cfg.depth))
        elif mode == "straddling":
            pages = math.ceil(cfg.width * cfg.depth / cells)
        else:
            raise ValueError(f"unknown geometry {mode}")
        if pages >= WIDE and cfg.family == "murmur32":
            raise ValueError("2^24 pages and more need family xx64")
        return cls(cfg, block_bytes, mode, pages)

    @property
    def family(self) -> str:
        """Keys are hashed to a page and to a column in it, never to the whole width."""
        return family_over(self.cfg.family, max(self.pages, self.columns + 1))

    @property
    def cells(self) -> int:
        """Counters of a page."""
        return self.block_bytes // self.cfg.cell_bytes

    @property
    def columns(self) -> int:
        """Columns of a page; straddling pages may have one more."""
        return self.cells // self.cfg.depth

    @property
    def total_columns(self) -> int:
        return self.pages * self.columns if self.mode == "aligned" else self.pages * self.cells // self.cfg.depth

    @property
    def effective_eps(self) -> float:
        return math.e / self.total_columns

    @property
    def size_bytes(self) -> int:
        return self.pages * self.block_bytes

    def fingerprint(self) -> str:
        return hashlib.md5(f"{self.cfg.fingerprint()}:{self.block_bytes}:{self.mode}".encode()).hexdigest()


@dataclass(frozen=True)
class BufferPlan:
    """Sub-buffers: capacity in elements of each, and amortized I/O of an update."""

    geom: PageGeometry
    ram_bits: int

    @classmethod
    def of(cls, geom: PageGeometry, ram_bits: int) -> BufferPlan:
        return cls(geom, ram_bits)

    @classmethod
    def oversubscribed(cls, geom: PageGeometry, ratio: float) -> BufferPlan:
        """RAM that is the sketch's size over ratio."""
        return cls(geom, int(geom.size_bytes * 8 / ratio))

    @property
    def raw_update_io(self) -> float:
        return self.geom.pages * self.geom.cfg.cell_bytes * 8 * self.geom.cfg.depth / self.ram_bits

    @property
    def update_io(self) -> float:
        return min(1.0, self.raw_update_io)

    @property
    def capacity(self) -> int:
        return max(1, math.floor(self.ram_bits / (self.geom.pages * self.geom.cfg.cell_bytes * 8 * self.geom.cfg.depth)))


#: Sketch sizes in MiB, RAM in MiB, failure probability and overestimate of the experiments.
SIZES_MIB = (128, 256, 512, 1024)
RAM_MIB = 64
DELTA, OVERESTIMATE = 0.01, 8
RATIOS = (2, 4, 8, 16)
