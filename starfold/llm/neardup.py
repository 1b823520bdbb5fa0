"""MinHash near-duplicates by ProbMinHash over weighted word shingles, banding and exact verification.

Equal texts collapse first. Texts that share a band meet at a pivot of their bucket, the text in most company; pairs are verified by their
exact probability Jaccard, and classes are the components of the verified links. Members of a bucket that are
then still in different classes are compared as well, unless their similarities to the pivot, the
shingles that no other open text has, or their signatures rule a link out. Pairs inside a class are never formed.

Defined results: null ids belong to no class and are left out of the links; texts without words are linked only
to equal texts; a null text is a class of its own. Texts, not ids, are what is linked: where an id repeats with
other text each of its texts has its own class, named by the least id of the class.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from starfold.llm import shingles as S
from starfold.llm.shared import discard, resting, stored
from starfold.operators.alternating import connected_components

THRESHOLD = 0.8
BANDS, ROWS = 25, 5


def with_bands(docs: DataFrame, *, words: int = 5, bands: int = BANDS, rows: int = ROWS, text: str = "text") -> DataFrame:
    """doc_id, digest of the text and one hash for each band; no bands where the text has no word."""
    base = docs.select("doc_id", F.md5(F.col(text).cast("binary")).alias("digest"), F.col(text).cast("binary").alias("_raw"))
    id_type = docs.schema["doc_id"].dataType.simpleString()

    def step(batches):
        for batch in batches:
            for at in _slices([len(x) if x is not None else 0 for x in batch.column(2).to_pylist()], 3 << 20, 30_000):
                part = batch.slice(*at)
                texts = [x or b"" for x in part.column(2).to_pylist()]
                h, own = S.shingle_hashes(texts, words)
                sig = S.signatures(*S.weighted(h, own), len(texts), bands * rows)
                some = np.bincount(own, minlength=len(texts)) > 0
                made = np.zeros((len(texts), bands), np.uint64)
                cells = sig.reshape(len(texts), bands, rows)
                for r in range(rows):
                    made += cells[:, :, r] * S.STEP[r]
                made = S.mix(made + np.arange(bands, dtype=np.uint64) * S.PLACE).view(np.int64)
                made[~some] = 0
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(np.where(some, bands, 0)))), pa.int32()), pa.array(made[some].reshape(-1)))
                # Seven bits of each register, seven registers a word: sums of words cannot overflow.
                spans = -(-bands * rows // 7)
                low = np.zeros((len(texts), spans * 7), np.uint8)
                low[:, :bands * rows] = (S.mix(sig) >> np.uint64(57)).astype(np.uint8)
                wide = np.zeros((len(texts), spans, 8), np.uint8)
                wide[:, :, :7] = low.reshape(len(texts), spans, 7)
                packed = wide.reshape(len(texts), spans * 8).view("<i8")
                sketch = pa.ListArray.from_arrays(pa.array(np.arange(len(texts) + 1) * packed.shape[1], pa.int32()), pa.array(packed.reshape(-1)))
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), lists, sketch], ["doc_id", "digest", "bands", "sketch"])

    return base.mapInArrow(resting(step), f"doc_id {id_type}, digest string, bands array<bigint>, sketch array<bigint>")


def _agreeing(a: str, b: str, registers: int):
    """Number of equal registers of two sketches: a byte of the difference carries into its top bit unless it is zero."""
    ones, tops = F.lit(0x7F7F7F7F7F7F7F).cast("bigint"), F.lit(0x80808080808080).cast("bigint")
    words = -(-registers // 7)
    total = F.lit(registers)
    for k in range(words):
        total = total - F.bit_count((F.col(a)[k].bitwiseXOR(F.col(b)[k]) + ones).bitwiseAND(tops))
    return total


def _slices(sizes: list[int], most: int, rows: int):
    first, held = 0, 0
    for k, n in enumerate(sizes):
        if k > first and (held + n > most or k - first >= rows):
            yield first, k - first
            first, held = k, 0
        held += n
    if sizes:
        yield first, len(sizes) - first


def similarities(pairs: DataFrame, texts: DataFrame, *, words: int = 5) -> DataFrame:
    """(a, b) with the exact probability Jaccard ``sim`` of their texts (vertex, raw)."""
    left = texts.select(F.col("vertex").alias("a"), F.col("raw").alias("ra"))
    right = texts.select(F.col("vertex").alias("b"), F.col("raw").alias("rb"))
    joined = pairs.join(left, "a").join(right, "b").select("a", "b", "ra", "rb")

    def step(batches):
        for batch in batches:
            ra, rb = batch.column(2).to_pylist(), batch.column(3).to_pylist()
            for first, n in _slices([len(x) + len(y) for x, y in zip(ra, rb)], 4 << 20, 8000):
                number: dict[bytes, int] = {}
                a, b = (np.array([number.setdefault(x, len(number)) for x in side[first:first + n]], np.int64) for side in (ra, rb))
                sim = S.probability_jaccards(list(number), a, b, words)
                part = batch.slice(first, n)
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(sim, pa.float64())], ["a", "b", "sim"])

    return joined.mapInArrow(resting(step), "a bigint, b bigint, sim double")


def own_shingles(members: DataFrame, texts: DataFrame, *, words: int = 5, bytes_per_part: int = 4 << 20) -> DataFrame:
    """For each of ``members`` (vertex): ``total`` weight of its shingles, ``excess`` of the weight over the number of
    different ones, and ``lone`` weight and ``lone_kinds`` of those that no other member has.

    Shingles travel packed, and one that several texts of a batch have travels once for the batch.
    """
    rows = members.join(texts, "vertex").select("vertex", "raw")
    record = np.dtype([("hash", "<u8"), ("vertex", "<i8"), ("weight", "<i4"), ("kind", "<i4")])
    parts = max(8, (rows.agg(F.sum(F.octet_length("raw"))).first()[0] or 0) // bytes_per_part)

    def pack(batches):
        for batch in batches:
            for at in _slices([len(x) for x in batch.column(1).to_pylist()], 4 << 20, 30_000):
                part = batch.slice(*at)
                vertex = np.array(part.column(0).to_pylist(), np.int64)
                h, own = S.shingle_hashes(part.column(1).to_pylist(), words)
                element, owner, weight = S.weighted(h, own)
                total, kinds = np.bincount(owner, weights=weight, minlength=len(vertex)), np.bincount(owner, minlength=len(vertex))
                # A record of kind 1 is the sums of a text, one of kind 0 a shingle; vertex -1 says that several texts have it.
                sums = np.zeros(len(vertex), record)
                sums["hash"], sums["vertex"], sums["weight"], sums["kind"] = kinds, vertex, total, 1
                order = np.argsort(element, kind="stable")
                element, owner, weight = element[order], owner[order], weight[order]
                first = np.flatnonzero(np.concatenate(([True], element[1:] != element[:-1])))[:len(element)]
                alone = np.diff(np.concatenate((first, [len(element)]))) == 1
                found = np.zeros(len(first), record)
                found["hash"], found["vertex"], found["weight"] = element[first], np.where(alone, vertex[owner[first]], -1), weight[first]
                home = np.concatenate((vertex % parts, (found["hash"] % np.uint64(parts)).astype(np.int64)))
                both = np.concatenate((sums, found))
                both = both[np.argsort(home, kind="stable")]
                cut = np.concatenate(([0], np.cumsum(np.bincount(home, minlength=parts))))
                full = np.flatnonzero(np.diff(cut))
                yield pa.RecordBatch.from_arrays([pa.array(full, pa.int32()), pa.array([both[cut[k]:cut[k + 1]].tobytes() for k in full], pa.binary())], ["part", "data"])

    def count(group: pa.Table) -> pa.Table:
        data = np.frombuffer(b"".join(group.column("data").to_pylist()), record)
        sums, found = data[data["kind"] == 1], data[data["kind"] == 0]
        found = found[np.argsort(found["hash"], kind="stable")]
        new = np.concatenate(([True], found["hash"][1:] != found["hash"][:-1]))[:len(found)]
        last = np.concatenate((new[1:], [True]))[:len(found)]
        lone = found[new & last & (found["vertex"] >= 0)]
        who, at = np.unique(lone["vertex"], return_inverse=True)
        zero = np.zeros(len(sums))
        cols = [
            np.concatenate((sums["vertex"], who)),
            np.concatenate((sums["weight"], np.zeros(len(who)))),
            np.concatenate((sums["weight"] - sums["hash"].astype(np.int64), np.zeros(len(who)))),
            np.concatenate((zero, np.bincount(at, weights=lone["weight"], minlength=len(who)))),
            np.concatenate((zero, np.bincount(at, minlength=len(who)))),
        ]
        return pa.table([pa.array(c.astype(np.int64)) for c in cols], ["vertex", "total", "excess", "lone", "lone_kinds"])

    counted = rows.mapInArrow(resting(pack), "part int, data binary").groupBy("part").applyInArrow(count, "vertex bigint, total bigint, excess bigint, lone bigint, lone_kinds bigint")
    return counted.groupBy("vertex").agg(*(F.sum(c).alias(c) for c in ("total", "excess", "lone", "lone_kinds")))


def most_similar(a: str, b: str):
    """Upper bound of the probability Jaccard of two texts with the figures of ``own_shingles``, columns named with prefixes ``a`` and ``b``.

    Let r and s be the shares of the weight of either text that the other does not have. Then the similarity is at
    most 1 / (1/(1-r) + s/(1-s)), and the same with r and s changed over, for each term of the sum is a concave
    function of degree one in the two shares of a shingle. Weight that no other text has is a part of r; so is all
    that is left once as many shingles match as the other text has shared ones.
    """
    col = lambda p, c: F.col(f"{p}{c}").cast("double")

    def unmatched(p, q):
        matches = col(q, "total") - col(q, "excess") - col(q, "lone_kinds") + col(p, "excess")
        return F.least(F.greatest(col(p, "lone") / col(p, "total"), 1 - matches / col(p, "total")), F.lit(1 - 1e-9))

    r, s = unmatched(a, b), unmatched(b, a)
    return F.least(1 / (1 / (1 - r) + s / (1 - s)), 1 / (r / (1 - r) + 1 / (1 - s)))


def _likely(rows: DataFrame, ids: DataFrame, most: int = 1 << 18) -> DataFrame:
    """Rows whose vertex may be in ``ids``: a bitmap of 32 bits an id, at most ``most`` words of 64, is sent to all tasks, so that other texts stay where they lie."""
    size = 1 << max(10, min(most.bit_length() - 1, (ids.count() // 2).bit_length()))
    word = F.expr(f"xxhash64(vertex) & {size - 1}")
    bit = F.expr("shiftleft(1L, cast(shiftrightunsigned(xxhash64(vertex), 40) & 63 as int))")
    marks = ids.groupBy(word.alias("_word")).agg(F.bit_or(bit).alias("_bits"))
    return rows.withColumns({"_word": word, "_bit": bit}).join(F.broadcast(marks), "_word").where("_bits & _bit <> 0").select(*rows.columns)


def _representatives(known: DataFrame) -> DataFrame:
    """One row for each text: digest, ``first`` (its least id) and ``vertex``, which is that id, or a number below all ids for the further texts of an id."""
    reps = stored(known.groupBy("digest").agg(F.min("doc_id").alias("first"), F.min_by("bands", "doc_id").alias("bands"), F.min_by("sketch", "doc_id").alias("sketch")))
    again = reps.groupBy("first").agg(F.count("*").alias("n"), F.min("digest").alias("least")).where("n > 1").select("first", "least")
    if again.isEmpty():
        return reps.withColumn("vertex", F.col("first"))
    further = stored(reps.select("first", "digest").join(again, "first").where("digest <> least").select("digest", F.monotonically_increasing_id().alias("k")))
    below = F.lit(min(reps.agg(F.min("first")).first()[0], 0)).cast("bigint") - 1
    return stored(reps.join(further, "digest", "left").withColumn("vertex", F.coalesce(below - F.col("k"), "first")).drop("k"))


def _classes(docs: DataFrame, *, words: int = 5, threshold: float = THRESHOLD, bands: int = BANDS, rows: int = ROWS, text: str = "text", block: int = 1024) -> tuple[DataFrame, bool]:
    """doc_id, digest, class_id and ``stays`` (the row's text is the one that its class keeps) of every row; and whether ids repeat."""
    signed = stored(with_bands(docs, words=words, bands=bands, rows=rows, text=text))
    known = signed.where("digest is not null and doc_id is not null")
    reps = _representatives(known)
    cells = reps.select("vertex", F.explode("bands").alias("bucket"))
    shared = cells.groupBy("bucket").agg(F.count("*").alias("n")).where("n > 1")
    members = stored(cells.join(shared, "bucket"))
    # The text in most company is the likeliest source of a family: as pivot it links the family at once.
    weight = members.groupBy("vertex").agg(F.sum("n").alias("weight"))
    members = stored(members.select("bucket", "vertex").join(weight, "vertex"))
    pivots = members.groupBy("bucket").agg(F.max_by("vertex", F.struct("weight", -F.col("vertex"))).alias("pivot"))
    met = members.join(pivots, "bucket").where("vertex <> pivot")
    tried = stored(met.select(F.least("vertex", "pivot").alias("a"), F.greatest("vertex", "pivot").alias("b")).distinct())
    needed = stored(members.select("vertex").distinct())
    # One row for each representative text that any pair can need: whole texts travel once.
    count = signed.where("doc_id is not null").agg(F.count("doc_id").alias("n"), F.count_distinct("doc_id").alias("k")).first()
    repeats = count.n != count.k
    raws = docs.select(F.col("doc_id").alias("vertex"), F.col(text).cast("binary").alias("raw")).where("raw is not null and vertex is not null")
    if repeats:
        named = needed.join(reps.select("vertex", "first", "digest"), "vertex")
        own = raws.withColumn("digest", F.md5("raw")).withColumnRenamed("vertex", "first")
        texts = stored(own.join(named, ["first", "digest"]).select("vertex", "raw").dropDuplicates(["vertex"]))
    else:
        texts = stored(_likely(raws, needed).join(needed, "vertex", "left_semi"))
    tested = stored(similarities(tried, texts, words=words))
    near = lambda df: df.where(F.col("sim") >= threshold - 1e-12).select("a", "b")
    links = stored(near(tested))
    found = stored(connected_components(links).labels)
    # Members of a bucket that are still in different classes. One less its similarity to the pivot is a distance, so
    # two members that are linked differ in it by at most the distance of a link: others need no test.
    placed = met.select("bucket", "vertex", F.least("vertex", "pivot").alias("a"), F.greatest("vertex", "pivot").alias("b")).join(tested, ["a", "b"])
    placed = placed.join(found, "vertex", "left").select("bucket", "vertex", "sim", F.coalesce("component", "vertex").alias("component"))
    placed = stored(placed)
    mixed = placed.groupBy("bucket").agg(F.min("component").alias("c1"), F.max("component").alias("c2")).where("c1 <> c2").select("bucket")
    open_ = stored(placed.join(mixed, "bucket").join(reps.select("vertex", "sketch", "bands"), "vertex"))
    # A text whose shingles are too often its own cannot be linked; what it has in common with no text bounds the rest.
    figures = stored(own_shingles(open_.select("vertex").distinct(), texts, words=words).where(F.col("lone") <= (1 - threshold + 1e-9) * F.col("total")))
    open_ = stored(open_.join(figures, "vertex"))
    mixed = open_.groupBy("bucket").agg(F.min("component").alias("c1"), F.max("component").alias("c2")).where("c1 <> c2").select("bucket")
    open_ = open_.join(mixed, "bucket", "left_semi")
    # A big bucket is dealt in blocks: its rows of the left side go to one block each, those of the right side to all.
    sizes = open_.groupBy("bucket").agg(F.count("*").alias("n"))
    open_ = open_.join(sizes, "bucket").withColumn("blocks", F.ceil(F.col("n") / block).cast("int")).drop("n")
    left, right = (open_.select([F.col(c).alias(f"{side}{c}") for c in open_.columns]) for side in ("l_", "r_"))
    left = left.withColumn("l_block", F.pmod(F.hash("l_vertex"), F.col("l_blocks")))
    right = right.withColumn("r_block", F.explode(F.sequence(F.lit(0), F.col("r_blocks") - 1)))
    close = F.abs(F.col("l_sim") - F.col("r_sim")) <= 1 - threshold + 1e-9
    # Registers agree with the similarity's chance: four deviations below the threshold nothing is linked but by a chance like that of missing every band.
    least = math.floor(bands * rows * threshold - 4 * math.sqrt(bands * rows * threshold * (1 - threshold)))
    alike = _agreeing("l_sketch", "r_sketch", bands * rows) >= least
    # A pair of several buckets is formed in the first; if one of the two is the pivot there, the pair has been tested.
    first = F.array_intersect("l_bands", "r_bands")[0] == F.col("l_bucket")
    pairs = left.join(right, (F.col("l_bucket") == F.col("r_bucket")) & (F.col("l_block") == F.col("r_block")) & (F.col("l_component") != F.col("r_component")) & (F.col("l_vertex") < F.col("r_vertex")) & close & (most_similar("l_", "r_") >= threshold - 1e-9) & alike & first)
    fresh = stored(pairs.select(F.col("l_vertex").alias("a"), F.col("r_vertex").alias("b")).distinct().join(tried, ["a", "b"], "left_anti"))
    more = stored(near(similarities(fresh, texts, words=words)))
    if not more.isEmpty():
        found = stored(connected_components(links.unionByName(more)).labels)
    labels = found.select(F.col("vertex").alias("_v"), F.col("component").alias("_c"))
    joined = reps.select("digest", "vertex", "first").join(labels, F.col("vertex") == F.col("_v"), "left").select("digest", "first", F.coalesce("_c", "vertex").alias("_c"))
    if repeats:
        best = joined.groupBy("_c").agg(F.min(F.struct("first", "digest")).alias("best"))
        joined = joined.join(best, "_c").select("digest", F.col("best.first").alias("class_id"), (F.col("digest") == F.col("best.digest")).alias("chosen"), "first")
    else:
        joined = joined.select("digest", F.col("_c").alias("class_id"), (F.col("first") == F.col("_c")).alias("chosen"), "first")
    stays = F.col("doc_id").isNull() | F.col("chosen").isNull() | (F.col("chosen") & (F.col("doc_id") == F.col("first")))
    out = signed.select("doc_id", "digest").join(joined, "digest", "left")
    out = out.select("doc_id", "digest", F.when(F.col("doc_id").isNotNull(), F.coalesce("class_id", "doc_id")).alias("class_id"), stays.alias("stays"))
    discard(members, placed, tried, tested, needed)
    return out, repeats


def classes(docs: DataFrame, **options) -> DataFrame:
    """doc_id and class_id, the least id among the texts that are linked, for every row of ``docs``; null for a null id."""
    return _classes(docs, **options)[0].select("doc_id", "class_id")


def keep_one(docs: DataFrame, *, text: str = "text", most_sent: int = 1_000_000, **options) -> DataFrame:
    """``docs`` with one document of each class, that of least id; of rows that repeat an id with its text one stays, rows without an id all stay."""
    found, repeats = _classes(docs, text=text, **options)
    gone = stored(found.where("not stays").select("doc_id", "digest").distinct())
    if not repeats:
        ids = gone.select("doc_id")
        # Up to a checked number the ids are sent to the texts, which then stay where they lie.
        return docs.join(F.broadcast(ids) if gone.count() <= most_sent else ids, "doc_id", "left_anti").select(*docs.columns)
    rows = docs.select(F.struct("*").alias("row"), F.col("doc_id"), F.md5(F.col(text).cast("binary")).alias("digest"))
    kept = rows.join(gone, ["doc_id", "digest"], "left_anti")
    named = kept.where("doc_id is not null and digest is not null").dropDuplicates(["doc_id", "digest"])
    return named.unionByName(kept.where("doc_id is null or digest is null")).select("row.*")
