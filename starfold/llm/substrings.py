"""Suffix-array dedup by bucket-pointer refinement, distributed.

Initial buckets are q-grams at the places that a window minimum selects, so every ``length``-byte string has one
and equal strings have the same. A bucket is refined by the bytes up to later offsets: all strings of one
minimum form a unit, and the identifier of a unit says whether whole runs of strings agree. Only where a bucket
falls into several units is it refined again, down to single strings. Documents lie in compressed chunks; what
travels is identifiers, folded within a chunk first, and the answers come back to the chunk as bits. Hence a
passage that a third of all documents share is one entry a chunk.

Equality is by polynomial hashes of the bytes: 96 bits and those of the bucket for a unit, 96 bits to two bases for
a single string. Two different ones of 10^13 agree with a chance of about one in a thousand. Defined results: a null text is empty; a null id is later
than every other; rows that repeat an id never cover each other; of equal texts all but those of least id are
removed whole if they have ``length`` bytes, and stay whole if not.
"""

from __future__ import annotations

import hashlib
import uuid

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from starfold.llm.shared import discard, stored
from starfold.llm.shingles import BYTE, mix

U = np.uint64
NULL_ID = (1 << 63) - 1
_BASES = {"first": 0x5851F42D4C957F2D, "second": 0x2545F4914F6CDD1D}
_POWERS: dict[str, np.ndarray] = {}


def _powers(n: int, which: str = "first") -> tuple[np.ndarray, np.ndarray]:
    """Powers of a base and of its inverse modulo 2^64, kept for the process."""
    if len(_POWERS.get(which + "up", ())) < n:
        size = max(n, 1 << 20)
        base = _BASES[which]
        for name, b in (("up", base), ("down", pow(base, -1, 1 << 64))):
            step = np.full(size, b, np.uint64)
            step[0] = 1
            _POWERS[which + name] = np.cumprod(step)
    return _POWERS[which + "up"][:n], _POWERS[which + "down"][:n]


class Chunk:
    """Units of a chunk of documents, in an order that does not depend on where it runs."""

    def __init__(self, data: bytes, lens: np.ndarray, ids: np.ndarray, skip: np.ndarray, length: int, gram: int):
        self.data, self.lens, self.ids, self.length = np.frombuffer(data, np.uint8), lens, ids, length
        ends = np.cumsum(lens)
        self.ends, self.begins = ends, ends - lens
        n, w = len(self.data), length - gram + 1
        empty = np.zeros(0, np.int64)
        self.start, self.owner, self.first_of = empty, empty, empty
        self.unit_lo = self.unit_n = self.unit_doc = empty
        if n < length:
            self.unit_hash, self.unit_anchor = np.zeros(0, np.uint64), np.zeros(0, np.uint64)
            self._fold()
            return
        up, down = _powers(n)
        self.down = down
        self.sums = np.zeros(n + 1, np.uint64)
        np.cumsum(BYTE[self.data] * up, out=self.sums[1:])
        h = mix((self.sums[gram:] - self.sums[:-gram]) * down[:n - gram + 1])
        value, place, width = h, np.arange(len(h), dtype=np.int32), 1
        while width < w:
            s = min(width, w - width)
            left = value[:-s] <= value[s:]
            place = np.where(left, place[:-s], place[s:])
            value = np.where(left, value[:-s], value[s:])
            width += s
        ok = (lens >= length) & ~skip
        counts = np.where(ok, lens - length + 1, 0)
        self.owner = np.repeat(np.arange(len(lens)), counts)
        self.start = np.arange(int(counts.sum())) + np.repeat(self.begins - (np.cumsum(counts) - counts), counts)
        at = place[self.start]
        if not len(at):
            self.unit_hash, self.unit_anchor = np.zeros(0, np.uint64), np.zeros(0, np.uint64)
            self._fold()
            return
        cut = np.flatnonzero(np.concatenate(([True], (at[1:] != at[:-1]) | (self.owner[1:] != self.owner[:-1]))))
        self.unit_lo = cut
        self.unit_n = np.diff(np.concatenate((cut, [len(at)])))
        lo = self.start[cut]
        hi = lo + self.unit_n - 1 + length
        self.unit_doc = self.owner[cut]
        self.unit_anchor = h[at[cut]]
        self.unit_hash = mix((self.sums[hi] - self.sums[lo]) * down[lo] + self.unit_n.astype(np.uint64))
        self._fold()

    def _fold(self) -> None:
        """One entry for each unit, of its least id in the chunk; entries go by id and hash."""
        doc_id = self.ids[self.unit_doc] if len(self.unit_doc) else np.zeros(0, np.int64)
        order = np.lexsort((doc_id, self.unit_hash))
        uh = self.unit_hash[order]
        head = np.concatenate(([True], uh[1:] != uh[:-1])) if len(uh) else np.zeros(0, bool)
        group = np.cumsum(head) - 1
        first = order[head]
        rank = np.lexsort((self.unit_hash[first], doc_id[first]))
        back = np.empty(len(rank), np.int64)
        back[rank] = np.arange(len(rank))
        self.entry = first[rank]
        self.entry_of = np.empty(len(order), np.int64)
        self.entry_of[order] = back[group]
        self.unit_id = doc_id
        self.entry_id = doc_id[self.entry]

    def strings(self, split: np.ndarray, dup: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Single strings of the units that are first of their kind in a bucket that split: places among ``start``, two hashes to different bases, and their ids."""
        e = self.entry_of
        take = (split[e] & ~dup[e] & (self.unit_id == self.entry_id[e])) if len(e) else np.zeros(0, bool)
        lo, n = self.unit_lo[take], self.unit_n[take]
        where = np.repeat(lo - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
        if not len(where):
            z = np.zeros(0, np.int64)
            return z, np.zeros(0, np.uint64), np.zeros(0, np.uint64), z
        s = self.start[where]
        h = mix((self.sums[s + self.length] - self.sums[s]) * self.down[s] + U(77))
        up, down = _powers(len(self.data), "second")
        sums = np.zeros(len(self.data) + 1, np.uint64)
        np.cumsum(mix(BYTE)[self.data] * up, out=sums[1:])
        g = mix((sums[s + self.length] - sums[s]) * down[s] + U(78))
        return where, h, g, self.ids[self.owner[where]]


def _fold_strings(h: np.ndarray, g: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Row of the least id of each pair of hashes, by (id, hashes), and the entry of each row."""
    order = np.lexsort((ids, g, h))
    hs, gs = h[order], g[order]
    head = np.concatenate(([True], (hs[1:] != hs[:-1]) | (gs[1:] != gs[:-1]))) if len(hs) else np.zeros(0, bool)
    group = np.cumsum(head) - 1
    first = order[head]
    rank = np.lexsort((g[first], h[first], ids[first]))
    back = np.empty(len(rank), np.int64)
    back[rank] = np.arange(len(rank))
    entry_of = np.empty(len(order), np.int64)
    entry_of[order] = back[group]
    return first[rank], entry_of


def _pack_ids(ids: np.ndarray) -> bytes:
    """Sorted ids as (count of runs, ids, run lengths)."""
    if not len(ids):
        return np.zeros(1, "<i8").tobytes()
    at = np.flatnonzero(np.concatenate(([True], ids[1:] != ids[:-1])))
    runs = np.diff(np.concatenate((at, [len(ids)])))
    return np.array([len(at)], "<i8").tobytes() + ids[at].astype("<i8").tobytes() + runs.astype("<u4").tobytes()


def _unpack_ids(raw: bytes) -> np.ndarray:
    k = int(np.frombuffer(raw, "<i8", 1)[0])
    return np.repeat(np.frombuffer(raw, "<i8", k, 8), np.frombuffer(raw, "<u4", k, 8 + 8 * k))


def chunked(docs: DataFrame, *, chunk_bytes: int = 4 << 20, text: str = "text") -> DataFrame:
    """Rows (part, chunk, ids, lens, digests, data): texts of about ``chunk_bytes`` in one compressed block; a longer text is a block of its own."""
    rows = docs.select(F.coalesce(F.col("doc_id").cast("bigint"), F.lit(NULL_ID)).alias("i"), F.coalesce(F.col(text).cast("binary"), F.lit(b"")).alias("t"))

    def step(batches):
        part = TaskContext.get().partitionId()
        press = zstandard.ZstdCompressor(level=3)
        held, size, k = [], 0, 0

        def flush():
            ids, texts = [i for i, _ in held], [t for _, t in held]
            digests = b"".join(hashlib.md5(t).digest() for t in texts)
            return pa.RecordBatch.from_arrays(
                [pa.array([part], pa.int32()), pa.array([(part << 32) + k], pa.int64()), pa.array([np.array(ids, "<i8").tobytes()], pa.binary()), pa.array([np.array([len(t) for t in texts], "<i8").tobytes()], pa.binary()), pa.array([digests], pa.binary()), pa.array([press.compress(b"".join(texts))], pa.binary())],
                ["part", "chunk", "ids", "lens", "digests", "data"],
            )

        for batch in batches:
            for at in range(0, batch.num_rows, 64):
                piece = batch.slice(at, 64)
                for i, t in zip(piece.column(0).to_pylist(), piece.column(1).to_pylist()):
                    if held and size + len(t) > chunk_bytes:
                        yield flush()
                        held, size, k = [], 0, k + 1
                    held.append((i, t))
                    size += len(t)
        if held:
            yield flush()

    return rows.mapInArrow(step, "part int, chunk bigint, ids binary, lens binary, digests binary, data binary")


def _as_table(df: DataFrame, parts: int) -> DataFrame:
    """The chunks as a table bucketed by part, so that later joins on part leave them where they are."""
    spark = df.sparkSession
    name = f"chunks_{uuid.uuid4().hex}"
    df.write.bucketBy(parts, "part").mode("overwrite").saveAsTable(name)
    out = spark.table(name)
    out._table_name = name
    return out


def _copies(chunks: DataFrame) -> DataFrame:
    """(chunk, place) of documents whose text equals that of a smaller id."""
    def step(batches):
        for batch in batches:
            for part, chunk, ids, digests in zip(*[batch.column(i).to_pylist() for i in range(4)]):
                i = np.frombuffer(ids, "<i8")
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(i), part, np.int32)), pa.array(np.full(len(i), chunk)), pa.array(np.arange(len(i), dtype=np.int32)), pa.array(i), pa.array([digests[16 * k:16 * k + 16] for k in range(len(i))], pa.binary())], ["part", "chunk", "place", "id", "digest"])

    rows = chunks.select("part", "chunk", "ids", "digests").mapInArrow(step, "part int, chunk bigint, place int, id bigint, digest binary")
    least = rows.groupBy("digest").agg(F.min("id").alias("least"), F.count("*").alias("n")).where("n > 1").select("digest", "least")
    late = rows.join(least, "digest").where("id > least")
    return late.groupBy("part").agg(F.collect_list(F.struct("chunk", "place")).alias("copies"))


def _answers(asked: DataFrame, step, schema: str) -> DataFrame:
    out = asked.groupBy("bucket").applyInPandas(step, schema)
    return out.groupBy("part").agg(F.collect_list(F.struct("chunk", "bucket", "bits")).alias("bits"))


def _opened(batch, length: int, gram: int):
    """(row index, Chunk, copy marks) of each row of a batch with part, chunk, ids, lens, data, copies first."""
    open_ = zstandard.ZstdDecompressor()
    for k in range(batch.num_rows):
        row = batch.slice(k, 1)
        chunk, ids, lens, data, copies = [row.column(i)[0].as_py() for i in range(1, 6)]
        ids, lens = np.frombuffer(ids, "<i8"), np.frombuffer(lens, "<i8")
        skip = np.zeros(len(ids), bool)
        skip[[c["place"] for c in copies or [] if c["chunk"] == chunk]] = True
        raw = open_.decompress(data) if len(data) else b""
        yield row, chunk, Chunk(raw, lens, ids, skip, length, gram), skip


def _cut(bucket: np.ndarray) -> tuple[np.ndarray, list[tuple[int, np.ndarray]]]:
    """Places sorted by bucket, and for each bucket that occurs its places in order; the work does not depend on how many buckets there are."""
    order = np.argsort(bucket, kind="stable")
    held = bucket[order]
    at = np.flatnonzero(np.concatenate(([True], held[1:] != held[:-1]))) if len(held) else np.zeros(0, np.int64)
    return order, list(zip(held[at].tolist(), np.split(order, at[1:]))) if len(at) else []


def _asked(row, chunk: int, bucket: np.ndarray, load):
    """Rows (bucket, part, chunk, n, load) of what a chunk asks each bucket that it has entries in."""
    _, rows = _cut(bucket)
    part, n = row.column(0)[0].as_py(), len(rows)
    return pa.RecordBatch.from_arrays(
        [pa.array([b for b, _ in rows], pa.int32()), pa.array([part] * n, pa.int32()), pa.array([chunk] * n, pa.int64()), pa.array([len(at) for _, at in rows], pa.int32()), pa.array([load(at) for _, at in rows], pa.binary())],
        ["bucket", "part", "chunk", "n", "load"],
    )


def _replies(row, index: int, chunk: int, bucket: np.ndarray, kinds: int) -> list[np.ndarray]:
    """The answer bits of every entry, one array a kind."""
    found = {b["bucket"]: b["bits"] for b in row.column(index)[0].as_py() or [] if b["chunk"] == chunk}
    out = [np.zeros(len(bucket), bool) for _ in range(kinds)]
    for b, at in _cut(bucket)[1]:
        raw = np.unpackbits(np.frombuffer(found.get(b, b""), np.uint8)).astype(bool)
        width = -(-len(at) // 8) * 8
        if len(raw):
            for k in range(kinds):
                out[k][at] = raw[k * width:k * width + len(at)]
    return out


def removed(docs: DataFrame, *, length: int = 50, gram: int = 26, chunk_bytes: int = 2 << 20, bucket_bytes: int = 16 << 20, text: str = "text", with_text: bool = False) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans and kept_sha256 of every row (and the kept bytes)."""
    spark = docs.sparkSession
    parts = max(4, int(spark.conf.get("spark.sql.shuffle.partitions")))
    chunks = _as_table(chunked(docs, chunk_bytes=chunk_bytes, text=text), parts)
    total = docs.agg(F.coalesce(F.sum(F.octet_length(text)), F.lit(0))).first()[0]
    nb = int(max(parts, total // bucket_bytes))
    copies = stored(_copies(chunks))
    slim = chunks.select("part", "chunk", "ids", "lens", "data")
    with_copies = slim.join(copies, "part", "left").select("part", "chunk", "ids", "lens", "data", "copies")

    def ask_units(batches):
        for batch in batches:
            for row, chunk, c, _ in _opened(batch, length, gram):
                anchor, unit, ids = c.unit_anchor[c.entry], c.unit_hash[c.entry], c.entry_id
                yield _asked(row, chunk, (anchor % U(nb)).astype(np.int64), lambda at: (anchor[at] >> U(32)).astype("<u4").tobytes() + unit[at].astype("<u8").tobytes() + _pack_ids(ids[at]))

    asked = with_copies.mapInArrow(ask_units, "bucket int, part int, chunk bigint, n int, load binary")

    def answer_units(pdf):
        ns = pdf["n"].to_numpy()
        a = np.concatenate([np.frombuffer(x, "<u4", n) for x, n in zip(pdf["load"], ns)])
        u = np.concatenate([np.frombuffer(x, "<u8", n, 4 * n) for x, n in zip(pdf["load"], ns)])
        d = np.concatenate([_unpack_ids(x[12 * n:]) for x, n in zip(pdf["load"], ns)])
        order = np.lexsort((u, a))
        sa, su, sd = a[order], u[order], d[order]
        new_a = np.concatenate(([True], sa[1:] != sa[:-1]))
        new_u = new_a | np.concatenate(([True], su[1:] != su[:-1]))
        heads = np.flatnonzero(new_u)
        group = np.cumsum(new_u) - 1
        low = np.minimum.reduceat(sd, heads)
        dup, split = np.zeros(len(a), bool), np.zeros(len(a), bool)
        dup[order] = sd > low[group]
        kinds = np.add.reduceat(new_u.astype(np.int64), np.flatnonzero(new_a))
        split[order] = (kinds > 1)[np.cumsum(new_a) - 1]
        out, at = [], 0
        for n in ns:
            out.append(np.packbits(dup[at:at + n]).tobytes() + np.packbits(split[at:at + n]).tobytes())
            at += n
        return pdf[["part", "chunk", "bucket"]].assign(bits=out)

    answer_schema = "part int, chunk bigint, bucket int, bits binary"
    units = stored(_answers(asked, answer_units, answer_schema))
    second = with_copies.join(units.withColumnRenamed("bits", "ub"), "part", "left")
    second = second.select("part", "chunk", "ids", "lens", "data", "copies", "ub")

    def unit_bits(row, chunk, c):
        return _replies(row, 6, chunk, (c.unit_anchor[c.entry] % U(nb)).astype(np.int64), 2)

    def ask_strings(batches):
        for batch in batches:
            for row, chunk, c, _ in _opened(batch, length, gram):
                dup, split = unit_bits(row, chunk, c)
                _, h, g, ids = c.strings(split, dup)
                entry, _ = _fold_strings(h, g, ids)
                h, g, ids = h[entry], g[entry], ids[entry]
                yield _asked(row, chunk, (h % U(nb)).astype(np.int64), lambda at: h[at].astype("<u8").tobytes() + (g[at] >> U(32)).astype("<u4").tobytes() + _pack_ids(ids[at]))

    def answer_strings(pdf):
        ns = pdf["n"].to_numpy()
        h = np.concatenate([np.frombuffer(x, "<u8", n) for x, n in zip(pdf["load"], ns)])
        g = np.concatenate([np.frombuffer(x, "<u4", n, 8 * n) for x, n in zip(pdf["load"], ns)])
        d = np.concatenate([_unpack_ids(x[12 * n:]) for x, n in zip(pdf["load"], ns)])
        order = np.lexsort((g, h))
        sh, sg, sd = h[order], g[order], d[order]
        new = np.concatenate(([True], (sh[1:] != sh[:-1]) | (sg[1:] != sg[:-1])))
        low = np.minimum.reduceat(sd, np.flatnonzero(new))
        dup = np.zeros(len(h), bool)
        dup[order] = sd > low[np.cumsum(new) - 1]
        out, at = [], 0
        for n in ns:
            out.append(np.packbits(dup[at:at + n]).tobytes())
            at += n
        return pdf[["part", "chunk", "bucket"]].assign(bits=out)

    asked2 = second.mapInArrow(ask_strings, "bucket int, part int, chunk bigint, n int, load binary")
    singles = stored(_answers(asked2, answer_strings, answer_schema))
    last = second.join(singles.withColumnRenamed("bits", "sb"), "part", "left").select("part", "chunk", "ids", "lens", "data", "copies", "ub", "sb")

    def finish(batches):
        for batch in batches:
            for row, chunk, c, skip in _opened(batch, length, gram):
                dup, split = unit_bits(row, chunk, c)
                flag = np.zeros(len(c.start), bool)
                if len(c.entry_of):
                    late = dup[c.entry_of] | (c.unit_id > c.entry_id[c.entry_of])
                    flag = np.repeat(late, c.unit_n)
                where, h, g, ids = c.strings(split, dup)
                if len(where):
                    entry, entry_of = _fold_strings(h, g, ids)
                    seen = _replies(row, 7, chunk, (h[entry] % U(nb)).astype(np.int64), 1)[0]
                    flag[where] = seen[entry_of] | (ids > ids[entry][entry_of])
                cover = np.zeros(len(c.data) + 1, np.int32)
                np.add.at(cover, c.start[flag], 1)
                np.add.at(cover, c.start[flag] + length, -1)
                gone = np.cumsum(cover[:-1]) > 0
                for k in np.flatnonzero(skip & (c.lens >= length)):
                    gone[c.begins[k]:c.ends[k]] = True
                n_removed, n_spans, sha, texts = [], [], [], []
                for a, b in zip(c.begins.tolist(), c.ends.tolist()):
                    g = gone[a:b]
                    n = int(np.count_nonzero(g))
                    n_removed.append(n)
                    n_spans.append(int(g[0]) + int(np.count_nonzero(g[1:] & ~g[:-1])) if n else 0)
                    kept = c.data[a:b].tobytes() if not n else c.data[a:b][~g].tobytes()
                    sha.append(hashlib.sha256(kept).hexdigest())
                    if with_text:
                        texts.append(kept)
                cols = [pa.array(c.ids), pa.array(c.lens), pa.array(n_removed, pa.int64()), pa.array(n_spans, pa.int64()), pa.array(sha, pa.string())]
                yield pa.RecordBatch.from_arrays(cols + ([pa.array(texts, pa.binary())] if with_text else []), ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"] + ["kept"] * with_text)

    out = last.mapInArrow(finish, "doc_id bigint, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string" + ", kept binary" * with_text)
    # The result is written, so that the chunks, which are as large as the texts, can go.
    result = stored(out.withColumn("doc_id", F.when(F.col("doc_id") != NULL_ID, F.col("doc_id"))))
    spark.sql(f"DROP TABLE {chunks._table_name}")
    discard(copies, units, singles)
    return result
