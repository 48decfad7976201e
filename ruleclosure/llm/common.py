"""Arrow buffers as numpy arrays, and small pieces that several operators share.

Python stages here work on *blocks*: consecutive rows whose texts hold at most ``BLOCK_BYTES`` bytes
together (one longer text is a block of its own), so the memory of a worker follows the block and
not the Arrow batch.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import Broadcast
from pyspark.sql import DataFrame

BLOCK_BYTES = 2_000_000

U64 = np.uint64
MASK64 = (1 << 64) - 1
#: Odd multipliers, so that they have inverses modulo 2**64.
BASE_A, BASE_B = 0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F


def sent(df: DataFrame, value) -> Broadcast:
    """The attributes of an object as a broadcast.  Broadcast values are pickled by reference to their class, which
    executors need not have; arrays and plain values travel alone and meet the class again in :func:`opened`."""
    return df.sparkSession.sparkContext.broadcast(vars(value))


def opened(kind: type, shared: Broadcast):
    value = kind.__new__(kind)
    value.__dict__.update(shared.value)
    return value


def free_name(name: str, taken: Iterable[str]) -> str:
    """``name``, with as many underscores behind it as make it differ from all taken names (in any case of letters)."""
    known = {x.lower() for x in taken}
    while name.lower() in known:
        name += "_"
    return name


def buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string or binary column; nulls become empty texts."""
    if column.null_count:
        column = pc.fill_null(column, pa.scalar("" if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else b"", column.type))
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offset_buffer, data = column.buffers()
    n = len(column)
    if n == 0 or offset_buffer is None:
        return np.zeros(0, np.uint8), np.zeros(n + 1, np.int64)
    kind = np.int64 if wide else np.int32
    offsets = np.frombuffer(offset_buffer, kind)[column.offset : column.offset + n + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def blocks(offsets: np.ndarray, limit: int = BLOCK_BYTES) -> Iterator[tuple[int, int]]:
    """Row ranges [a, b) whose texts hold at most ``limit`` bytes, or one row."""
    n, a = len(offsets) - 1, 0
    while a < n:
        b = int(np.searchsorted(offsets, offsets[a] + limit, side="right")) - 1
        b = min(max(b, a + 1), n)
        yield a, b
        a = b


def text_blocks(batch: pa.RecordBatch, column: str, limit: int = BLOCK_BYTES):
    """(first row, last row + 1, bytes, offsets within them) for each block of a batch."""
    raw, offsets = buffers(batch.column(batch.schema.get_field_index(column)))
    for a, b in blocks(offsets, limit):
        yield a, b, raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]


def lower_table() -> np.ndarray:
    """Byte table that lower-cases A-Z only."""
    table = np.arange(256, dtype=np.uint8)
    table[65:91] += 32
    return table


_POWERS: dict[int, np.ndarray] = {}


def powers(base: int, n: int) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2**64; those of one block's length are remembered."""
    known = _POWERS.get(base)
    if known is None or len(known) < n:
        known = np.full(max(n, 1), base, U64)
        known[0] = 1
        known = np.cumprod(known, dtype=U64)
        if n <= 2 * BLOCK_BYTES:
            _POWERS[base] = known
    return known[:n]


def inverse(base: int) -> int:
    """The inverse of an odd number modulo 2**64."""
    return pow(base, -1, 1 << 64)


def mix(h: np.ndarray) -> np.ndarray:
    """Spread the bits of 64-bit values (an invertible finaliser)."""
    h = h ^ (h >> U64(33))
    h = h * U64(0xFF51AFD7ED558CCD)
    h = h ^ (h >> U64(33))
    h = h * U64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> U64(33))


class Spans:
    """Hashes of any spans of one sequence, from prefix sums of a polynomial modulo 2**64."""

    def __init__(self, values: np.ndarray, base: int = BASE_A):
        n = len(values)
        self.undo = powers(inverse(base), n + 1)
        self.sums = np.zeros(n + 1, U64)
        np.cumsum(values.astype(U64) * powers(base, n), out=self.sums[1:])

    def hash(self, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        return mix((self.sums[ends] - self.sums[starts]) * self.undo[starts])


def row_of(offsets: np.ndarray) -> np.ndarray:
    """For each byte, the index of its row."""
    return np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))
