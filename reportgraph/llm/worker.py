"""What Python workers hold. A worker is used again by later tasks, so what an operator leaves in it adds to the memory of the operators after it."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa

#: Rows whose texts a worker holds as Python objects at a time; a batch has up to 10,000.
SLICE_ROWS = 512

_HELD: dict[tuple[str, str], object] = {}


def turn(owner: str) -> None:
    """Drops what other operators hold in this process."""
    for key in [k for k in _HELD if k[0] != owner]:
        del _HELD[key]
    pa.default_memory_pool().release_unused()


def held(owner: str, key: str, make: Callable[[], object]):
    """What an operator keeps from task to task in this process, until another operator's turn."""
    turn(owner)
    if (owner, key) not in _HELD:
        _HELD[owner, key] = make()
    return _HELD[owner, key]


def slices(batches: Iterator[pa.RecordBatch], rows: int = SLICE_ROWS) -> Iterator[pa.RecordBatch]:
    """The rows of batches, few at a time; an empty batch has none."""
    for b in batches:
        for i in range(0, b.num_rows, rows):
            yield b.slice(i, rows)
