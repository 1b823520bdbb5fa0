"""Benchmark decontamination by a generalised suffix automaton of the test items.

The automaton holds every run of words of every item. A document's words stream through it; the longest
matching length at each word says which windows end there. Words are normalised as bytes, so any text is one
stream. Runs of words whose neighbouring pairs never stand together in an item cannot hold a window of two
words or more and are skipped before the walk.

Items are read in blocks of at most ``block_bytes`` of text, so one automaton has a proven size; with more
blocks the rows pass through one narrow step per block. Defined results: a null text has no words; an item
without words has no window; an empty benchmark marks nothing; repeated rows are marked alike.
"""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from starfold.llm.shared import WORD_BYTES, text_words

WORD = re.compile(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


class SuffixAutomaton:
    """Generalised automaton over word numbers; ``window`` words make a window, shorter items are one window."""

    def __init__(self, items: list[tuple[str, list[bytes]]], window: int):
        self.window = window
        self.vocabulary: dict[bytes, int] = {}
        number = self.vocabulary
        coded = [(i, [number.setdefault(w, len(number)) for w in ws]) for i, ws in items if ws]
        self.go: list[dict[int, int]] = [{}]
        self.link, self.length = [-1], [0]
        for _, ws in coded:
            last = 0
            for w in ws:
                last = self._extend(last, w)
        self.items: list[set] = [set() for _ in self.go]
        self.short: list[list] = [[] for _ in self.go]
        self.anchor = [self._climb(s, window) for s in range(len(self.go))]
        for i, ws in coded:
            s = 0
            for k, w in enumerate(ws):
                s = self.go[s][w]
                if k + 1 >= window:
                    self.items[self.anchor[s]].add(i)
            if len(ws) < window:
                self.short[self._climb(s, len(ws))].append((len(ws), i))
        for s in sorted(range(1, len(self.go)), key=self.length.__getitem__):
            self.short[s] = self.short[s] + self.short[self.link[s]]
        self.least = min((min(window, len(ws)) for _, ws in coded), default=0)
        pairs = {(a, b) for _, ws in coded for a, b in zip(ws, ws[1:])}
        self.n = max(1, len(number))
        codes = np.array(sorted(a * self.n + b for a, b in pairs), np.int64)
        self.table = None
        if self.n * self.n <= 1 << 27:
            self.table = np.zeros(self.n * self.n, bool)
            self.table[codes] = True
        self.codes = codes

    def _extend(self, last: int, w: int) -> int:
        go, link, length = self.go, self.link, self.length
        if w in go[last]:
            q = go[last][w]
            if length[q] == length[last] + 1:
                return q
            return self._split(last, w, q)
        cur = len(go)
        go.append({})
        link.append(0)
        length.append(length[last] + 1)
        p = last
        while p != -1 and w not in go[p]:
            go[p][w] = cur
            p = link[p]
        if p != -1:
            q = go[p][w]
            link[cur] = q if length[q] == length[p] + 1 else self._split(p, w, q)
        return cur

    def _split(self, p: int, w: int, q: int) -> int:
        go, link, length = self.go, self.link, self.length
        clone = len(go)
        go.append(dict(go[q]))
        link.append(link[q])
        length.append(length[p] + 1)
        link[q] = clone
        while p != -1 and go[p].get(w) == q:
            go[p][w] = clone
            p = link[p]
        return clone

    def _climb(self, s: int, least: int) -> int:
        while s > 0 and self.length[self.link[s]] >= least:
            s = self.link[s]
        return s

    def _runs(self, ids: np.ndarray) -> list[tuple[int, int]]:
        if self.least <= 1:
            ok = ids >= 0
            need = 1
        else:
            a, b = ids[:-1], ids[1:]
            known = (a >= 0) & (b >= 0)
            code = np.where(known, a * self.n + b, 0)
            if self.table is not None:
                ok = known & self.table[code]
            else:
                at = np.minimum(np.searchsorted(self.codes, code), max(0, len(self.codes) - 1))
                ok = known & (self.codes[at] == code) if len(self.codes) else known & False
            need = self.least - 1
        edges = np.flatnonzero(np.diff(np.concatenate(([0], ok.view(np.int8), [0]))))
        starts, ends = edges[::2], edges[1::2]
        keep = ends - starts >= need
        more = 0 if self.least <= 1 else 1
        return [(int(s), int(e) + more) for s, e in zip(starts[keep], ends[keep])]

    def scan(self, words: list[bytes]) -> tuple[list[tuple[int, int]], set]:
        """Merged spans of hit words, and the items with a window that occurs."""
        if not self.least or len(words) < self.least:
            return [], set()
        get = self.vocabulary.get
        ids = np.array([get(w, -1) for w in words], np.int64)
        spans: list[list[int]] = []
        found: set = set()
        go, link, length = self.go, self.link, self.length
        for start, end in self._runs(ids):
            s, n = 0, 0
            for k in range(start, end):
                w = int(ids[k])
                while s and w not in go[s]:
                    s = link[s]
                    n = length[s]
                if w in go[s]:
                    s = go[s][w]
                    n += 1
                else:
                    n = 0
                hit = 0
                if n >= self.window:
                    hit = self.window
                    found |= self.items[self.anchor[s]]
                for size, item in self.short[s]:
                    if size <= n:
                        hit = max(hit, size)
                        found.add(item)
                if hit:
                    a, b = k + 1 - hit, k + 1
                    while spans and spans[-1][1] >= a and spans[-1][0] >= a:
                        spans.pop()
                    if spans and spans[-1][1] >= a:
                        spans[-1][1] = b
                    else:
                        spans.append([a, b])
        return [tuple(x) for x in spans], found


def automata(benchmark: DataFrame, window: int, block_bytes: int = 16 << 20, item: str = "item_id", text: str = "text") -> list[SuffixAutomaton]:
    """One automaton for each block of items; a block's text is at most ``block_bytes`` by a count of all items."""
    items = benchmark.select(F.col(item).cast("string").alias("i"), F.col(text).alias("t")).where("i is not null and t is not null")
    total = items.agg(F.coalesce(F.sum(F.octet_length("t")), F.lit(0))).first()[0]
    blocks = 1 if total <= block_bytes else -(-2 * total // block_bytes)
    out = []
    for k in range(blocks):
        rows = (items if blocks == 1 else items.where(F.pmod(F.xxhash64("i", "t"), F.lit(blocks)) == k)).collect()
        out.append(SuffixAutomaton([(r.i, text_words(r.t)) for r in sorted(rows, key=lambda r: (r.i, r.t))], window))
    return out


def mark(docs: DataFrame, benchmark: DataFrame, *, window: int = 10, text: str = "text", block_bytes: int = 16 << 20) -> DataFrame:
    """Adds n_words, hit_starts and hit_ends (word places), hit_items and hit_bytes (byte places of the spans)."""
    extra = "n_words bigint, hit_starts array<int>, hit_ends array<int>, hit_items array<string>"
    clash = [c for c in docs.columns if c in ("n_words", "hit_starts", "hit_ends", "hit_items")]
    if clash:
        raise ValueError(f"columns that would be lost: {clash}")
    sc = docs.sparkSession.sparkContext
    first = True
    for automaton in automata(benchmark, window, block_bytes):
        held = sc.broadcast(automaton)
        names = docs.columns

        def step(batches, held=held, names=names, first=first):
            for batch in batches:
                cols = dict(zip(batch.schema.names, batch.columns))
                texts = cols[text].to_pylist()
                before = None if first else list(zip(cols["hit_starts"].to_pylist(), cols["hit_ends"].to_pylist(), cols["hit_items"].to_pylist()))
                n, starts, ends, items = [], [], [], []
                for k, t in enumerate(texts):
                    ws = text_words(t)
                    spans, found = held.value.scan(ws)
                    if before:
                        spans = _merge([*spans, *zip(before[k][0], before[k][1])])
                        found = found | set(before[k][2])
                    n.append(len(ws))
                    starts.append([a for a, _ in spans])
                    ends.append([b for _, b in spans])
                    items.append(sorted(found))
                keep = [cols[c] for c in names if c not in ("n_words", "hit_starts", "hit_ends", "hit_items")]
                made = [pa.array(n, pa.int64()), pa.array(starts, pa.list_(pa.int32())), pa.array(ends, pa.list_(pa.int32())), pa.array(items, pa.list_(pa.string()))]
                fixed = [c for c in names if c not in ("n_words", "hit_starts", "hit_ends", "hit_items")]
                yield pa.RecordBatch.from_arrays(keep + made, [*fixed, "n_words", "hit_starts", "hit_ends", "hit_items"])

        schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema if f.name not in ("n_words", "hit_starts", "hit_ends", "hit_items"))
        docs = docs.mapInArrow(step, f"{schema}, {extra}")
        first = False
    return docs


def _merge(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [tuple(x) for x in out]


def report(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """The digest columns of each document."""
    marked = mark(docs.select("doc_id", "text"), benchmark, **options)
    hits = F.aggregate(F.zip_with("hit_ends", "hit_starts", lambda e, s: (e - s).cast("bigint")), F.lit(0).cast("bigint"), lambda a, x: a + x)
    return marked.select(
        "doc_id", "n_words", hits.alias("n_hit"), F.size("hit_items").cast("long").alias("n_items"),
        F.sha2(F.array_join("hit_items", ",").cast("binary"), 256).alias("items_sha256"), (F.size("hit_items") > 0).alias("contaminated"),
    )


def cut_spans(text: str, starts: list[int], ends: list[int]) -> str:
    """The text without the words of the spans and what lies between them."""
    raw = text.encode("utf-8", "surrogatepass")
    places = [m.span() for m in WORD.finditer(raw.translate(WORD_BYTES))]
    out, at = [], 0
    for a, b in zip(starts, ends):
        out.append(raw[at:places[a][0]])
        at = places[b - 1][1]
    out.append(raw[at:])
    return b"".join(out).decode("utf-8", "surrogatepass")


def clean(docs: DataFrame, benchmark: DataFrame, *, window: int = 10, max_coverage: float = 0.5, text: str = "text", **options) -> DataFrame:
    """``docs`` without contamination: spans are cut, and a document of which more than ``max_coverage`` is hit goes.

    Columns are those of ``docs``; n_chars, where there is one, follows the text.
    """
    rows = docs.select(F.struct("*").alias("row"), F.col(text).alias("text"))
    marked = mark(rows, benchmark, window=window, **options)
    hits = F.aggregate(F.zip_with("hit_ends", "hit_starts", lambda e, s: (e - s).cast("bigint")), F.lit(0).cast("bigint"), lambda a, x: a + x)
    kept = marked.where(hits <= F.col("n_words") * max_coverage).withColumn("cut", F.size("hit_starts") > 0)
    schema = kept.select("row", "text", "cut").schema

    def step(batches):
        for batch in batches:
            cols = dict(zip(batch.schema.names, batch.columns))
            texts = cols["text"].to_pylist()
            starts, ends = cols["hit_starts"].to_pylist(), cols["hit_ends"].to_pylist()
            cols["text"] = pa.array([cut_spans(t, a, b) if a else t for t, a, b in zip(texts, starts, ends)], pa.string())
            yield pa.RecordBatch.from_arrays([cols[c] for c in schema.names], schema.names)

    touched = kept.mapInArrow(step, schema)

    def column(c: str):
        if c == text:
            return F.col("text").alias(c)
        if c == "n_chars":
            return F.when(F.col("cut"), F.length("text").cast(docs.schema[c].dataType)).otherwise(F.col("row.n_chars")).alias(c)
        return F.col(f"row.`{c}`")

    return touched.select(*[column(c) for c in docs.columns])
