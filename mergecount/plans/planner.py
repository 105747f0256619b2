"""Cells or packed: the form whose shuffle is smaller for the expected tasks and groups."""

from __future__ import annotations

from dataclasses import dataclass

from ..params import SketchParams

CELL_ROW_BYTES = 24


@dataclass(frozen=True)
class Choice:
    form: str
    cell_rows: int
    cell_bytes: int
    packed_bytes: int


def shuffled(params: SketchParams, blobs, per_group=None):
    """Bytes of both forms, cells and packed, when so many blobs (tasks x groups) are sent; numbers or columns."""
    size = params.l * params.b
    return blobs * (size if per_group is None else per_group) * CELL_ROW_BYTES, blobs * (size * (2 * params.budget + 1) / 8 + 32)


def choose(params: SketchParams, tasks: int, groups: int, rows: int | None = None) -> Choice:
    """Shuffled bytes of either form: a task sends at most l * b cells, or one packed blob, for each group it meets."""
    met = groups if rows is None else min(groups, max(1, rows // max(tasks, 1)))
    per_group = params.l * params.b if rows is None else min(params.l * params.b, params.l * max(1, rows // max(groups, 1)))
    cell_rows = tasks * met * per_group
    cell_bytes, packed = shuffled(params, tasks * met, per_group)
    return Choice("cells" if cell_bytes <= packed else "packed", cell_rows, cell_bytes, int(packed))

