"""Best-fit packing of token sequences, improved by a swap-based local search.

Documents are tokenized where they lie and only (id, piece, length) rows travel. Pieces are dealt by hash into
groups of a fixed expected size, each packed by one task: best fit in falling order, then exchanges between
underfull bins - a move, one piece for one, two for one - each of which raises the sum of squared fills, until
bins empty or no exchange is left.

Defined results: a null or empty text is the closing id alone. Repeated rows are packed each for itself.
"""

from __future__ import annotations

import bisect
import functools
import heapq
import os
import re
import struct
import zlib
from collections import defaultdict

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from starfold.llm.shared import resting

CLOSING_ID = 1


class CachedTokenizer:
    """Token ids of a text as little-endian bytes, from a cache of its chunks.

    For a vocabulary that lower-cases, drops white space and splits between letters or digits and signs, the ids of
    a text are those of its lower-cased chunks, cut at ASCII white space and before the signs that end a word. A
    text that may hold an added token, which is matched before all that, is cut at white space alone. The cache has
    two generations of ``limit`` chunks: a chunk that is met again moves to the younger one, and the older is dropped
    when the younger is full. It holds no chunk of more than ``longest`` bytes, so its memory is bounded (about 0.13 GB
    at the default); a Python worker keeps it from task to task of a stage.
    """

    #: Chunks that are encoded at once.
    BATCH = 2000
    #: ASCII signs between an ASCII letter or digit and white space or the end.
    LAST_SIGNS = re.compile(rb"([!-/:-@\[-`{-~](?<=[a-z0-9].)[!-/:-@\[-`{-~]*)(?=\s|$)")

    def __init__(self, path: str, limit: int = 300_000, longest: int = 96):
        # Every task has a core of its own: threads inside it would only hold memory.
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.cache: dict[bytes, bytes] = {}
        self.old: dict[bytes, bytes] = {}
        self.limit, self.longest = limit, longest
        self.added = [t.content.encode() for t in self.tok.get_added_tokens_decoder().values()]

    def chunks(self, text: bytes) -> list[bytes]:
        low = text.lower()
        return text.split() if any(t in low for t in self.added) else self.LAST_SIGNS.sub(rb" \1", low).split()

    def encode(self, texts: list[bytes]) -> list[bytes]:
        split = [self.chunks(t) for t in texts]
        if len(self.cache) > self.limit:
            self.old, self.cache = self.cache, {}
        cache, old = self.cache, self.old
        new = set().union(*split).difference(cache)
        again = new.intersection(old)
        cache.update((w, old[w]) for w in again)
        new -= again
        long = [w for w in new if len(w) > self.longest]
        missing = list(new.difference(long))
        step = self.BATCH
        for part in [*([w] for w in long), *(missing[at:at + step] for at in range(0, len(missing), step))]:
            for w, e in zip(part, self.tok.encode_batch_fast([w.decode("utf-8", "replace") for w in part], add_special_tokens=False)):
                ids = e.ids
                cache[w] = struct.pack(f"<{len(ids)}I", *ids)
        get = cache.__getitem__
        out = [b"".join(map(get, ws)) for ws in split]
        for w in long:
            del cache[w]
        return out


@functools.lru_cache(maxsize=1)
def worker_tokenizer(path: str) -> CachedTokenizer:
    """One tokenizer, and one cache, for all tasks of a Python worker."""
    return CachedTokenizer(path)


def drop_tokenizer() -> None:
    worker_tokenizer.cache_clear()


def tokenized_pieces(docs: DataFrame, tokenizer: str, *, limit: int = 4096, text: str = "text", with_ids: bool = False) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 for each piece of at most ``limit`` ids (and the ids themselves)."""
    closing = np.array([CLOSING_ID], "<u4").tobytes()
    id_type = docs.schema["doc_id"].dataType.simpleString()

    def step(batches):
        tok = worker_tokenizer(tokenizer)
        for whole in batches:
            for at in range(0, whole.num_rows, 256):
                batch = whole.slice(at, 256)
                ids = batch.column(0)
                texts = [t or b"" for t in batch.column(1).to_pylist()]
                take, piece, start, length, crc, raw = [], [], [], [], [], []
                for k, data in enumerate(tok.encode(texts)):
                    data += closing
                    for p, s in enumerate(range(0, len(data), 4 * limit)):
                        part = data[s:s + 4 * limit]
                        take.append(k)
                        piece.append(p)
                        start.append(s // 4)
                        length.append(len(part) // 4)
                        crc.append(zlib.crc32(part))
                        if with_ids:
                            raw.append(part)
                cols = [ids.take(pa.array(take, pa.int32())), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64())]
                names = ["doc_id", "piece", "start", "length", "ids_crc32"]
                yield pa.RecordBatch.from_arrays(cols + ([pa.array(raw, pa.binary())] if with_ids else []), names + ["ids"] * with_ids)

    schema = f"doc_id {id_type}, piece int, start bigint, length bigint, ids_crc32 bigint" + ", ids binary" * with_ids
    return docs.select("doc_id", F.col(text).cast("binary").alias("text")).mapInArrow(resting(step, drop_tokenizer), schema)


def best_fit(sizes: np.ndarray, capacity: int) -> list[list[int]]:
    """Best fit in falling order; bit r of ``open_`` says that a bin with r free places exists."""
    bins: list[list[int]] = []
    free: dict[int, list[int]] = defaultdict(list)
    open_ = 0
    for i in np.argsort(-sizes, kind="stable").tolist():
        size = int(sizes[i])
        fit = open_ >> size
        if fit:
            room = size + (fit & -fit).bit_length() - 1
            b = free[room].pop()
            if not free[room]:
                open_ &= ~(1 << room)
            bins[b].append(i)
        else:
            b, room = len(bins), capacity
            bins.append([i])
        left = room - size
        if left:
            free[left].append(b)
            open_ |= 1 << left
    return bins


class Search:
    """Swap-based local search over the underfull bins of one group.

    Bins are taken as victims in rising order of fill. A victim gives fill to fuller bins, which raises the sum of
    squared fills: a move, one piece for one, or one for two. For every piece size the bins that hold it are kept in
    order of their free places, so the widest exchange of one piece for one is a look at one array; sums of two
    sizes are bits of an integer, kept for each amount of free places. A victim is worked on until it is empty or no
    exchange is left, once a pass; each exchange takes a place from it at least, so a pass makes ``capacity``
    exchanges a bin at most. The search ends at the volume bound, when a pass finds no exchange, or after ``idle``
    passes that emptied no bin.
    """

    def __init__(self, bins: list[list[int]], sizes: np.ndarray, capacity: int, idle: int = 8):
        self.size = sizes.tolist()
        self.bins = bins
        self.idle = idle
        self.free = [capacity - sum(self.size[i] for i in b) for b in bins]
        self.pairs: list[int | None] = [None] * len(bins)
        self.bound = -(-int(sizes.sum()) // capacity)
        self.span = capacity + 1
        self.place = np.arange(self.span)

    def _open(self, order: list[int]) -> None:
        """Index the bins that may receive."""
        self.rooms: list[tuple[int, int]] = []
        self.holders: dict[int, list[tuple[int, int]]] = defaultdict(list)
        self.reach = np.full(self.span, -1, np.int64)  # size + most free places of a bin that holds it
        self.order: list[tuple[int, int]] = []
        self.at: dict[int, set[int]] = defaultdict(set)
        self.sums: dict[int, int] = {}
        for b in order:
            self._enter(b)

    def _enter(self, b: int) -> None:
        room = self.free[b]
        if room:
            bisect.insort(self.rooms, (room, b))
            self.at[room].add(b)
            self.sums.pop(room, None)
            for y in {self.size[i] for i in self.bins[b]}:
                held = self.holders[y]
                bisect.insort(held, (room, b))
                self.reach[y] = y + held[-1][0]

    def _leave(self, b: int) -> None:
        room = self.free[b]
        if room:
            del self.rooms[bisect.bisect_left(self.rooms, (room, b))]
            self.at[room].discard(b)
            self.sums.pop(room, None)
            if not self.at[room]:
                del self.at[room]
            for y in {self.size[i] for i in self.bins[b]}:
                held = self.holders[y]
                del held[bisect.bisect_left(held, (room, b))]
                self.reach[y] = y + held[-1][0] if held else -1

    def _pair_sums(self, b: int) -> int:
        if self.pairs[b] is None:
            once = out = 0
            for i in self.bins[b]:
                out |= once << self.size[i]
                once |= 1 << self.size[i]
            self.pairs[b] = out
        return self.pairs[b]

    def _trade(self, victim: int, give: int, other: int, take: list[int]) -> None:
        self._leave(other)
        self.bins[victim].remove(give)
        for i in take:
            self.bins[other].remove(i)
        self.bins[victim] += take
        self.bins[other].append(give)
        gain = self.size[give] - sum(self.size[i] for i in take)
        self.free[victim] += gain
        self.free[other] -= gain
        self.pairs[victim] = self.pairs[other] = None
        self._enter(other)
        heapq.heappush(self.order, (-self.free[other], other))

    def _exchange(self, victim: int) -> bool:
        """One exchange that takes fill from ``victim``; False where there is none."""
        if not self.rooms:
            return False
        mine: dict[int, int] = {}
        for i in self.bins[victim]:
            mine.setdefault(self.size[i], i)
        order = sorted(mine.items(), reverse=True)
        for s, i in order:
            k = bisect.bisect_left(self.rooms, (s, -1))
            if k < len(self.rooms):
                self._trade(victim, i, self.rooms[k][1], [])
                return True
        best = (0, 0, 0)
        for s, i in order:
            if s > best[0]:
                y = int((self.reach[1:s] >= s).argmax()) + 1 if s > 1 else 0
                if y and self.reach[y] >= s and s - y > best[0]:
                    best = (s - y, i, y)
        if best[0]:
            _, i, y = best
            other = self.holders[y][-1][1]
            self._trade(victim, i, other, [next(j for j in self.bins[other] if self.size[j] == y)])
            return True
        for s, i in order:
            for room in sorted(self.at, reverse=True):
                if room not in self.sums:
                    held = 0
                    for b in self.at[room]:
                        held |= self._pair_sums(b)
                    self.sums[room] = held
                low = max(2, s - room)
                fit = self.sums[room] >> low
                y = low + (fit & -fit).bit_length() - 1
                if fit and y < s:
                    other = min(b for b in self.at[room] if self._pair_sums(b) >> y & 1)
                    self._trade(victim, i, other, self._two(other, y))
                    return True
        return False

    def _two(self, b: int, total: int) -> list[int]:
        seen: dict[int, int] = {}
        for i in self.bins[b]:
            if total - self.size[i] in seen:
                return [seen[total - self.size[i]], i]
            seen.setdefault(self.size[i], i)
        raise LookupError(total)

    def run(self) -> list[list[int]]:
        count, idle = len(self.bins), 0
        while count > self.bound and idle < self.idle:
            left = {b for b in range(len(self.bins)) if self.bins[b] and self.free[b]}
            self._open(sorted(left))
            self.order = [(-self.free[b], b) for b in left]
            heapq.heapify(self.order)
            before, moved = count, False
            while self.order:
                room, victim = heapq.heappop(self.order)
                if victim not in left or -room != self.free[victim]:
                    continue
                # Only bins that have not been victims in this pass, which are no less full, receive.
                left.remove(victim)
                self._leave(victim)
                while self.bins[victim] and self._exchange(victim):
                    moved = True
                if not self.bins[victim]:
                    count -= 1
                    if count <= self.bound:
                        break
            if not moved:
                break
            idle = 0 if count < before else idle + 1
        return [b for b in self.bins if b]


def local_search(bins: list[list[int]], sizes: np.ndarray, capacity: int) -> list[list[int]]:
    """Bins with as many emptied by exchanges as ``Search`` can."""
    return Search(bins, sizes, capacity).run()


def pack(pieces: DataFrame, *, capacity: int = 4096, group_size: int = 16384, expected: int | None = None) -> DataFrame:
    """Adds sequence_id and offset. ``expected`` is about the number of pieces and sets how many groups there are."""
    groups = max(1, -(-(expected if expected is not None else pieces.count()) // group_size))
    names = pieces.columns
    dealt = pieces.withColumn("_group", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(groups)))

    def solve(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["length", "doc_id", "piece", "ids_crc32"], ascending=[False, True, True, True], kind="stable").reset_index(drop=True)
        sizes = pdf["length"].to_numpy(np.int64)
        bins = local_search(best_fit(sizes, capacity), sizes, capacity)
        seq, off = np.zeros(len(pdf), np.int64), np.zeros(len(pdf), np.int64)
        base = int(pdf["_group"].iat[0]) << 32
        for b, members in enumerate(bins):
            at = 0
            for i in members:
                seq[i], off[i] = base + b, at
                at += int(sizes[i])
        pdf["sequence_id"], pdf["offset"] = seq, off
        return pdf[[*names, "sequence_id", "offset"]]

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in pieces.schema)
    # A count given by hand is not folded by the adaptive planner, which would put many groups in one task.
    return dealt.repartition(groups, "_group").groupBy("_group").applyInPandas(solve, f"{schema}, sequence_id bigint, offset bigint")


def pack_documents(docs: DataFrame, tokenizer: str, *, capacity: int = 4096, group_size: int = 16384) -> DataFrame:
    """Every document of ``docs`` as pieces in sequences of at most ``capacity`` ids."""
    return pack(tokenized_pieces(docs, tokenizer, limit=capacity), capacity=capacity, group_size=group_size, expected=docs.count())
