"""Sizes on the wire and settings of a synchronisation."""

from __future__ import annotations

from dataclasses import dataclass, field


@dataclass(frozen=True)
class WireModel:
    """Bytes of a digest, of a coded cell (id, check, count) and of a bucket index; payloads count as they are."""

    digest: int = 8
    cell: int = 24
    bucket_index: int = 4


#: Parts of a replica that make a segment, where the number of segments is left open: what one decoding task holds.
SEGMENT_PARTS = 50_000


def segments_for(parts: int) -> int:
    return max(1, -(-parts // SEGMENT_PARTS))


@dataclass(frozen=True)
class SyncConfig:
    """segments: digest ranges reconciled apart, by default as many as the replicas' sizes ask for; first_cells and growth: the slices
    of the coded stream, longer where the cells so far tell of more differences. eps (0: no filter) and load_factor: where they are
    given, they hold for all sessions; else each session's own, or 1 % and one bucket a part.
    """

    wire: WireModel = field(default_factory=WireModel)
    segments: int | None = None
    first_cells: int = 64
    growth: int = 4
    eps: float | None = None
    load_factor: float | None = None
