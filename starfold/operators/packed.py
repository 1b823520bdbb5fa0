"""Pairs of vertices packed as bytes, a row for a slice: they are exchanged and stored whole, and sorted in numpy.

Pairs are of longs. A row is (kind, slot, n, pairs); the slot of a pair is dealt by its first vertex.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

SCHEMA = "kind string, slot int, n long, pairs binary"
_ARROW = pa.schema([("kind", pa.string()), ("slot", pa.int32()), ("n", pa.int64()), ("pairs", pa.binary())])
#: Pairs of a row and bytes of a batch, at most.
ROW_PAIRS, BATCH_BYTES = 1 << 20, 1 << 24
#: Labels that a task holds before it drops repeated ones and sends the others.
HELD = 1 << 23
_MASK = (1 << 64) - 1
_NONE = np.empty(0, np.int64)

Pairs = tuple[np.ndarray, np.ndarray]


def _narrow(x: np.ndarray) -> tuple[int, int, bytes]:
    """Least value, bytes a value, and the differences to the least in as few bytes."""
    low, high = int(x.min()), int(x.max())
    width = next(w for w in (1, 2, 4, 8) if high - low < 1 << 8 * w)
    return low, width, (x.astype(np.uint64) - np.uint64(low & _MASK)).astype(f"u{width}").tobytes()


def pack(a: np.ndarray, b: np.ndarray) -> bytes:
    """Pairs sorted by their first vertex, each of these written once."""
    first = np.flatnonzero(np.r_[True, a[1:] != a[:-1]])
    parts = [_narrow(x) for x in (a[first], np.diff(np.r_[first, len(a)]), b)]
    head = np.array([len(first), len(a), *(v for low, width, _ in parts for v in (low, width))], np.int64)
    return head.tobytes() + b"".join(x for _, _, x in parts)


def unpack(data: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First vertices, how many pairs each has, and second vertices."""
    head, at, out = np.frombuffer(data, np.int64, 8).tolist(), 64, []
    for n, low, width in ((head[0], *head[2:4]), (head[0], *head[4:6]), (head[1], *head[6:8])):
        out.append((np.frombuffer(data, f"u{width}", n, at).astype(np.uint64) + np.uint64(low & _MASK)).view(np.int64))
        at += n * width
    return tuple(out)


def unseen(a: np.ndarray, b: np.ndarray, seen: Pairs = (_NONE, _NONE)) -> Pairs:
    """The distinct pairs that are not among those seen, sorted. Sorts one long for each pair if two fit into it."""
    if not len(a):
        return _NONE, _NONE
    new = np.r_[np.zeros(len(seen[0]), np.int64), np.ones(len(a), np.int64)]
    a, b = np.r_[seen[0], a], np.r_[seen[1], b]
    low_a, low_b = int(a.min()), int(b.min())
    bits_a, bits_b = ((int(x.max()) - low).bit_length() for x, low in ((a, low_a), (b, low_b)))
    if bits_a + bits_b < 63:
        key = ((a - low_a) << (bits_b + 1)) | ((b - low_b) << 1) | new
        key.sort()
        pair = key >> 1
        pair = pair[np.r_[True, pair[1:] != pair[:-1]] & (key & 1 == 1)]
        return (pair >> bits_b) + low_a, (pair & ((1 << bits_b) - 1)) + low_b
    order = np.lexsort((new, b, a))
    a, b, new = a[order], b[order], new[order]
    take = np.r_[True, (a[1:] != a[:-1]) | (b[1:] != b[:-1])] & (new == 1)
    return a[take], b[take]


def slot_of(v: np.ndarray, slots: int) -> np.ndarray:
    x = v.astype(np.uint64)
    x = (x ^ (x >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    return ((x ^ (x >> np.uint64(33))) % np.uint64(slots)).astype(np.uint16 if slots <= 1 << 16 else np.int64)


def dealt(kind: str, a: np.ndarray, b: np.ndarray, slots: int) -> Iterator[tuple]:
    """Rows of sorted pairs by the slot of the first vertex."""
    if not len(a):
        return
    slot = slot_of(a, slots)
    order = np.argsort(slot, kind="stable")
    a, b, slot = a[order], b[order], slot[order]
    ends = np.r_[np.flatnonzero(slot[1:] != slot[:-1]) + 1, len(a)]
    start = 0
    for end in ends.tolist():
        for i in range(start, end, ROW_PAIRS):
            j = min(end, i + ROW_PAIRS)
            yield kind, int(slot[i]), j - i, pack(a[i:j], b[i:j])
        start = end


def batched(rows: Iterator[tuple]) -> Iterator[pa.RecordBatch]:
    held, size = [], 0
    for row in rows:
        held.append(row)
        size += len(row[3]) + 64
        if size >= BATCH_BYTES:
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*held), _ARROW)], schema=_ARROW)
            held, size = [], 0
    if held:
        yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*held), _ARROW)], schema=_ARROW)


def _rows(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[str, bytes]]:
    for batch in batches:
        yield from zip(batch.column("kind").to_pylist(), batch.column("pairs").to_pylist())


def _all(data: list[bytes]) -> Pairs:
    """Pairs of several rows, one after another."""
    parts = [unpack(d) for d in data]
    if not parts:
        return _NONE, _NONE
    return np.concatenate([np.repeat(a, n) for a, n, _ in parts]), np.concatenate([b for _, _, b in parts])


def placing(slots: int):
    """Rows of (larger, smaller) as packed labels told to the larger vertex."""
    def place(batches):
        def rows():
            held, size = [], 0
            for batch in batches:
                held.append((batch.column(0).to_numpy(), batch.column(1).to_numpy()))
                size += batch.num_rows
                if size >= HELD:
                    yield from dealt("told", *unseen(*map(np.concatenate, zip(*held))), slots)
                    held, size = [], 0
            if held:
                yield from dealt("told", *unseen(*map(np.concatenate, zip(*held))), slots)

        yield from batched(rows())

    return place


def merging(slots: int):
    """For the rows of a slot: told labels that are no neighbours yet become such, with their twins for other slots."""
    def merge(batches):
        def rows():
            told, down = [], []
            for kind, data in _rows(batches):
                (told if kind == "told" else down).append(data)
            a, b = unseen(*_all(told), _all(down))
            yield from dealt("down", a, b, slots)
            yield from dealt("up", *unseen(b, a), slots)

        yield from batched(rows())

    return merge


def telling(slots: int):
    """For the rows of a slot: labels after the fresh edges, and what they tell to which vertex.

    Over fresh edges every label is told, over old ones those that fell.
    """
    def tell(batches):
        def rows():
            found: dict[str, list[bytes]] = {k: [] for k in ("labels", "down", "up", "fresh_down", "fresh_up")}
            for kind, data in _rows(batches):
                found[kind].append(data)
            near, least = unseen(*_all(found["fresh_down"]))
            first = np.r_[True, near[1:] != near[:-1]][: len(near)]
            near, least = near[first], least[first]
            if found["labels"]:
                v, m = _all(found["labels"])
                order = np.argsort(v)
                v, m = v[order], m[order]
                at = np.searchsorted(v, near)
                lower = least < m[at]
                fell = np.zeros(len(v), bool)
                fell[at[lower]] = True
                m[at[lower]] = least[lower]
            else:
                v = np.unique(np.r_[near, *(unpack(d)[0] for d in found["fresh_up"])])
                m, fell = v.copy(), np.ones(len(v), bool)
                m[np.searchsorted(v, near)] = least
            yield from dealt("labels", v, m, slots)
            held, size = [], 0
            for kind in ("down", "up", "fresh_down", "fresh_up"):
                for data in found[kind]:
                    src, n, u = unpack(data)
                    at = np.searchsorted(v, src)
                    label = np.repeat(m[at], n)
                    take = label != u
                    if not kind.startswith("fresh"):
                        take &= np.repeat(fell[at], n)
                    held.append((u[take], label[take]))
                    size += len(held[-1][0])
                    if size >= HELD:
                        yield from dealt("told", *unseen(*map(np.concatenate, zip(*held))), slots)
                        held, size = [], 0
            if held:
                yield from dealt("told", *unseen(*map(np.concatenate, zip(*held))), slots)

        yield from batched(rows())

    return tell


def spread(batches):
    """Packed rows as pairs."""
    for batch in batches:
        for data in batch.column("pairs").to_pylist():
            a, n, b = unpack(data)
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(a, n)), pa.array(b)], ["src", "dst"])
