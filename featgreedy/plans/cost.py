"""Bytes that each execution mode moves, and the choice among them."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Shape:
    n: int
    d: int
    columns: int
    blocks: int
    selected_columns: int
    steps: int
    winners: int
    nodes: int = 16
    executors: int = 16
    segments: int = 1


def estimates(s: Shape) -> dict[str, float]:
    """``wire``: atoms and updates of every round; ``state``: one scan and one broadcast per distinct winner; ``gram``:
    one scan and a matrix of all columns; ``pruned_gram``: a scan of the selected blocks alone."""
    scan = s.n * s.columns * 8
    return {
        "wire": s.steps * s.nodes * (2 * (s.n + s.d) + 5) * 8 + s.steps * scan,
        "state": s.winners * (s.n * 8 * s.executors + scan / s.segments) + s.steps * s.columns * s.d * 8,
        "gram": scan + s.columns**2 * 8 * 2,
        "pruned_gram": s.n * s.selected_columns * 8 + s.selected_columns**2 * 8 * 2,
    }


def choose(s: Shape, driver_bytes: int = 512_000_000) -> str:
    e = estimates(s)
    options = ["wire", "state"] + (["gram"] if s.columns**2 * 8 <= driver_bytes else [])
    return min(options, key=e.get)


def explain(s: Shape) -> str:
    e = estimates(s)
    return "\n".join(f"{'->' if k == choose(s) else '  '} {k:12s} {v / 1e9:12.3f} GB" for k, v in e.items())
