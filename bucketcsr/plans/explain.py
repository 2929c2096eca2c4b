"""Why a build or probe is planned as it is."""

from __future__ import annotations

from ..operators.probe import choose_probe
from .params import BuildSpec, resolve


def explain_build(n: int, spec: BuildSpec = BuildSpec()) -> str:
    layout = resolve(n, spec)
    how = "bytes" if spec.bins == "auto" else "request"
    return (
        f"{n} rows, load {spec.load:g}: V = {layout.v} buckets; {layout.bins} bins of {layout.width} buckets by {how}; "
        f"{layout.parts} parts of about {max(1, n // layout.parts)} rows. Exchanges: bin counts (one number per bin and task), rows once (pass-through)."
    )


def explain_probe(index_bytes: int, index_stored: bool, probe_stored: bool, appearances: float, mode: str = "all") -> str:
    kind, reason = choose_probe(index_bytes, index_stored, probe_stored, appearances, mode)
    moved = 0 if (index_stored and probe_stored) or (kind == "lookup" and "broadcast" in reason) else 1 if index_stored or kind == "lookup" else 2
    return f"{kind}: {reason}. Exchanges of rows: {moved}."
