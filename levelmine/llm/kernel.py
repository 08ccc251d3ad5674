"""Vectorised text kernels over Arrow string columns: word boundaries, word hashes, n-gram hashes.

Everything works on the UTF-8 bytes of a block of rows at once. Hashes are polynomial sums modulo 2**64 taken from
prefix sums, so any window of bytes or words costs O(1); a final mixer spreads them.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Rows are cut into blocks of about so many bytes; one longer text is a block of its own.
BLOCK_BYTES = 1 << 19

_U = np.uint64


def byte_table(word_bytes: Iterator[int]) -> np.ndarray:
    table = np.zeros(256, np.bool_)
    table[list(word_bytes)] = True
    return table


#: Bytes of words: all but the white space 0x20 and 0x09 to 0x0D.
NON_SPACE = byte_table(b for b in range(256) if b != 0x20 and not 0x09 <= b <= 0x0D)

LOWER = np.arange(256, dtype=np.uint8)
LOWER[ord("A") : ord("Z") + 1] += 32


def _inverse(odd: int) -> int:
    return pow(odd, -1, 1 << 64)


#: So many powers are kept, a little more than a block has bytes.
_POWERS_KEPT = (1 << 19) + (1 << 12)


class _Powers:
    """Powers of an odd number and of its inverse modulo 2**64. Those for blocks are kept; a longer text's are not."""

    def __init__(self, base: int):
        self.base, self.kept = base, None

    def _made(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        steps = np.full(n, self.base, _U)
        steps[0] = 1
        up = np.multiply.accumulate(steps)
        steps[1:] = _inverse(self.base)
        return up, np.multiply.accumulate(steps)

    def of(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if n > _POWERS_KEPT:
            return self._made(n)
        if self.kept is None:
            self.kept = self._made(_POWERS_KEPT)
        return self.kept[0][:n], self.kept[1][:n]


_BYTE_POWERS = _Powers(0x9E3779B97F4A7C15)
_WORD_POWERS = _Powers(0xD1342543DE82EF95)
_BYTE_VALUES = np.random.default_rng(7).integers(1, 2**63, 256, dtype=np.int64).astype(_U) * _U(2) + _U(1)


def mix(x: np.ndarray, salt: int = 0) -> np.ndarray:
    """A 64-bit finaliser; different salts give independent looking values."""
    x = x ^ _U(salt * 0x9E3779B97F4A7C15 % (1 << 64))
    x ^= x >> _U(33)
    x *= _U(0xFF51AFD7ED558CCD)
    x ^= x >> _U(33)
    x *= _U(0xC4CEB9FE1A85EC53)
    x ^= x >> _U(33)
    return x


def give_back() -> None:
    """Returns freed memory of this process to the system, where the C library can; workers outlive their tasks."""
    import ctypes
    import gc

    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):
        pass


class Words:
    """The words of a block: bytes, byte range of each word, and for each row the range of its words."""

    __slots__ = ("buf", "row_bytes", "start", "end", "ptr")

    def __init__(self, buf: np.ndarray, row_bytes: np.ndarray, word_bytes: np.ndarray):
        self.buf, self.row_bytes = buf, row_bytes
        n = len(buf)
        if n:
            inside = word_bytes[buf]
            cut = np.zeros(n + 1, np.bool_)
            cut[row_bytes] = True
            first = inside.copy()
            first[1:] &= ~inside[:-1] | cut[1:n]
            last = inside.copy()
            last[:-1] &= ~inside[1:] | cut[1:n]
            self.start, self.end = np.flatnonzero(first), np.flatnonzero(last) + 1
        else:
            self.start = self.end = np.zeros(0, np.int64)
        self.ptr = np.searchsorted(self.start, row_bytes)

    def counts(self) -> np.ndarray:
        return np.diff(self.ptr)

    def row_of_word(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.ptr) - 1), self.counts())

    def hashes(self) -> np.ndarray:
        """A 64-bit hash of each word."""
        n = len(self.buf)
        up, down = _BYTE_POWERS.of(n + 1)
        total = np.zeros(n + 1, _U)
        np.cumsum(_BYTE_VALUES[self.buf] * up[:n], out=total[1:])
        return mix((total[self.end] - total[self.start]) * down[self.start])

    def joined(self, keep: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Kept words of each row joined by one space: bytes, and the rows' offsets into them."""
        buf, n = self.buf, len(self.buf)
        start, end, rows = self.start, self.end, self.row_of_word()
        if keep is not None:
            start, end, rows = start[keep], end[keep], rows[keep]
        step = np.zeros(n + 1, np.int8)
        step[start] += 1
        step[end] -= 1  # a word's end may be the next row's first byte, hence the sum
        mask = np.zeros(n + 1, np.bool_)
        mask[:n] = np.cumsum(step[:n], dtype=np.int8) > 0
        if len(rows):
            gap = end[:-1][rows[1:] == rows[:-1]]  # in the row, so a separator
            buf = buf.copy()
            buf[gap] = 0x20
            mask[gap] = True
        offsets = np.zeros(n + 1, np.int64)
        np.cumsum(mask[:n], out=offsets[1:])
        return buf[mask[:n]], offsets[self.row_bytes]


def gram_hashes(words: np.ndarray, n: int) -> np.ndarray:
    """Hash of the n consecutive word hashes from each position on; positions with fewer left are absent."""
    m = len(words)
    if m < n:
        return np.zeros(0, _U)
    up, down = _WORD_POWERS.of(m + 1)
    total = np.zeros(m + 1, _U)
    np.cumsum(words * up[:m], out=total[1:])
    return mix((total[n:] - total[:-n]) * down[: m + 1 - n])


def within_rows(ptr: np.ndarray, n: int) -> np.ndarray:
    """For each n-gram position of a block: whether the n words lie in one row."""
    m = int(ptr[-1])
    ok = np.ones(max(0, m + 1 - n), np.bool_)
    for back in range(1, n):  # positions whose window crosses a row's end
        at = ptr[1:-1] - back
        at = at[(at >= 0) & (at < len(ok))]
        ok[at] = False
    return ok


def text_bytes(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and row offsets of a string column; null counts as empty."""
    return cell_bytes(column, pa.large_string(), "")


def cell_bytes(column: pa.Array | pa.ChunkedArray, kind: pa.DataType | None = None, null: str | bytes = b"") -> tuple[np.ndarray, np.ndarray]:
    """Bytes of all cells of a binary column, one after the other, and where each begins; null counts as empty."""
    kind = kind or pa.large_binary()
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
        if isinstance(column, pa.ChunkedArray):
            column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], kind)
    if column.null_count:
        column = pc.fill_null(column, null)
    column = column.cast(kind)
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    buf = np.frombuffer(data, np.uint8)[at[0] : at[-1]] if data is not None else np.zeros(0, np.uint8)
    return buf, at - at[0]


def cells(data: np.ndarray, ends: np.ndarray) -> pa.Array:
    """A binary column whose cell i is the bytes ends[i]..ends[i + 1] of data."""
    body = np.ascontiguousarray(data).view(np.uint8)
    return pa.Array.from_buffers(pa.binary(), len(ends) - 1, [None, pa.py_buffer(ends.astype(np.int32).tobytes()), pa.py_buffer(body)])


def run_edges(x: np.ndarray) -> np.ndarray:
    """Where the runs of a sorted array begin, and its end."""
    if not len(x):
        return np.zeros(1, np.int64)
    return np.concatenate([[0], np.flatnonzero(x[1:] != x[:-1]) + 1, [len(x)]])


def blocks(offsets: np.ndarray, size: int = BLOCK_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of rows of about size bytes."""
    n, lo = len(offsets) - 1, 0
    while lo < n:
        hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + size, "right")) - 1)
        yield lo, min(hi, n)
        lo = min(hi, n)


def word_blocks(column: pa.Array, word_bytes: np.ndarray = NON_SPACE, lower: bool = False) -> Iterator[tuple[int, int, Words]]:
    buf, at = text_bytes(column)
    for lo, hi in blocks(at):
        part = buf[at[lo] : at[hi]]
        yield lo, hi, Words(LOWER[part] if lower else part, at[lo : hi + 1] - at[lo], word_bytes)


#: The constants of the XXH64 format: fixed values.
_P1, _P2, _P3, _P4, _P5 = (_U(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def _turn(x: np.ndarray, r: int) -> np.ndarray:
    return (x << _U(r)) | (x >> _U(64 - r))


def xxh64(buf: np.ndarray, start: np.ndarray, end: np.ndarray, seed: int = 42) -> np.ndarray:
    """XXH64 of many byte ranges of one buffer, lane by lane over all ranges at once."""
    pad = np.concatenate([buf, np.zeros(8, np.uint8)])
    wide = np.ndarray(len(buf) + 1, "<u8", pad, strides=(1,))
    half = np.ndarray(len(buf) + 1, "<u4", pad, strides=(1,))
    at, left = start.astype(np.int64), (end - start).astype(np.int64)
    size, wrap = left.astype(_U), lambda x: _U(x % (1 << 64))
    p1, p2 = int(_P1), int(_P2)
    h = np.full(len(at), wrap(seed + int(_P5)), _U)
    big = np.flatnonzero(left >= 32)
    if len(big):
        lanes = [np.full(len(big), v, _U) for v in map(wrap, (seed + p1 + p2, seed + p2, seed, seed - p1))]
        live, live_at, live_left = np.arange(len(big)), at[big], left[big]
        while len(live):
            for i in range(4):
                lanes[i][live] = _turn(lanes[i][live] + wide[live_at + 8 * i] * _P2, 31) * _P1
            live_at, live_left = live_at + 32, live_left - 32
            at[big[live]], left[big[live]] = live_at, live_left
            more = live_left >= 32
            live, live_at, live_left = live[more], live_at[more], live_left[more]
        acc = _turn(lanes[0], 1) + _turn(lanes[1], 7) + _turn(lanes[2], 12) + _turn(lanes[3], 18)
        for lane in lanes:
            acc = (acc ^ (_turn(lane * _P2, 31) * _P1)) * _P1 + _P4
        h[big] = acc
    h += size
    live = np.flatnonzero(left >= 8)
    while len(live):
        h[live] = _turn(h[live] ^ (_turn(wide[at[live]] * _P2, 31) * _P1), 27) * _P1 + _P4
        at[live] += 8
        left[live] -= 8
        live = live[left[live] >= 8]
    live = np.flatnonzero(left >= 4)
    h[live] = _turn(h[live] ^ (half[at[live]].astype(_U) * _P1), 23) * _P2 + _P3
    at[live] += 4
    left[live] -= 4
    live = np.flatnonzero(left > 0)
    while len(live):
        h[live] = _turn(h[live] ^ (pad[at[live]].astype(_U) * _P5), 11) * _P1
        at[live] += 1
        left[live] -= 1
        live = live[left[live] > 0]
    h ^= h >> _U(33)
    h *= _P2
    h ^= h >> _U(29)
    h *= _P3
    return h ^ (h >> _U(32))
