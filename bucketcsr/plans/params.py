"""How many buckets, bins and parts an index has."""

from __future__ import annotations

from dataclasses import dataclass, field
from math import ceil

from ..functions.hashing import HashSpec

#: An exchange keeps at most so many partitions.
MOST_PARTS = 32_768


@dataclass(frozen=True)
class BuildSpec:
    """load C: rows per bucket on average, V = ceil(N / C). bins: an integer, or 'auto' by bytes.

    parts: shuffle partitions of the layout (None: by bytes); payload 'row' keeps rid and payload columns, 'key' keys alone.
    """

    load: float = 1.0
    buckets: int | None = None
    bins: int | str = "auto"
    parts: int | None = None
    hash: HashSpec = field(default_factory=HashSpec)
    payload: str = "row"
    row_bytes: int = 16
    target_bin_bytes: int = 128 << 20
    target_part_bytes: int = 512 << 20
    hot_bucket_rows: int | None = None

    def hot_limit(self) -> int:
        """Rows of a bucket above which it is kept in pieces (default: what fits in a part)."""
        return self.hot_bucket_rows or max(1, self.target_part_bytes // self.row_bytes)


@dataclass(frozen=True)
class Layout:
    """Resolved sizes: n rows, v buckets, bins of `width` neighbouring buckets."""

    n: int
    v: int
    bins: int
    width: int
    parts: int


def bucket_count(n: int, load: float) -> int:
    if load <= 0:
        raise ValueError("the load must be positive")
    return max(1, ceil(n / load))


def choose_bins(n: int, row_bytes: int, target: int, v: int) -> int:
    """Bins by bytes, never more than buckets."""
    return max(1, min(v, ceil(n * row_bytes / target)))


def choose_load(builds: int, probes: int) -> float:
    """Between 1 and 2: fewer buckets where building prevails, shorter lists where probing does."""
    if builds < 0 or probes < 0:
        raise ValueError("row counts can't be negative")
    total = builds + probes
    return 1.0 if total == 0 else round(1 + builds / total, 3)


def resolve(n: int, spec: BuildSpec, v: int | None = None, other_rows: int = 0) -> Layout:
    """other_rows: rows of a second index in the same layout, counted for the part sizes."""
    v = v or spec.buckets or bucket_count(n, spec.load)
    wanted = choose_bins(n, spec.row_bytes, spec.target_bin_bytes, v) if spec.bins == "auto" else int(spec.bins)
    if wanted < 1:
        raise ValueError("at least one bin is needed")
    width = ceil(v / min(wanted, v))
    bins = ceil(v / width)
    parts = spec.parts or max(1, ceil((n + other_rows) * spec.row_bytes / spec.target_part_bytes))
    return Layout(n, v, bins, width, max(1, min(parts, bins, MOST_PARTS)))


def work_terms(n: int, v: int, bins: int, cores: int, binned: bool) -> dict[str, float]:
    """Operation counts of a build: hash calls, counter sweeps, prefix steps, placements; and their share per core."""
    hashes = 3 * n if binned else n
    sweeps = 2 * v + (2 * bins if binned else 0)
    moves = 2 * n if binned else n
    prefix = v + (bins if binned else 0)
    work = hashes + sweeps + prefix + moves + n
    return {"hashes": hashes, "sweeps": sweeps, "prefix": prefix, "moves": moves, "work": work, "per_core": work / cores}


def storage_elements(n: int, v: int, bins: int, binned: bool, payload: str = "row") -> dict[str, int]:
    """Elements held: the table, two counters per bucket, bin counters, and the reorganised copy of a binned build."""
    table = n * (2 if payload == "row" else 1)
    return {"table": table, "buckets": 2 * v, "bins": 2 * bins if binned else 0, "reorganised": table if binned else 0}


def capacity(memory_bytes: int, load: float, binned: bool, entry_bytes: int = 8, counter_bytes: int = 4) -> int:
    """Most rows whose index and counters fit in so much memory."""
    per_row = entry_bytes * (2 if binned else 1) + 2 * counter_bytes / load
    return int(memory_bytes // per_row)
