"""Null, empty, repeated and clashing rows for every operator, and the chain of stages."""

import hashlib
import hmac
import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from starfold.llm import decontaminate, language, licenses, neardup, packing, private, quality, shared, sharding, substrings, toxicity
from starfold.llm.queries import TOKENIZER

VOCAB = [f"{a}{b}" for a in ("ka", "lo", "mi", "nu", "re", "sa", "ti", "vo") for b in ("ber", "dan", "fin", "gol", "hup", "jem", "kar", "lin")]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
CLASH = ["_m", "_f", "row", "t", "m", "n_words", "hit_starts", "hit_items", "_row", "grp", "digest", "vertex", "raw", "_text", "bands", "score", "shard", "slot", "_key", "piece", "length", "_group", "bucket", "line", "kept", "class_id"]


def prose(n, seed):
    return " ".join(np.random.default_rng(seed).choice(VOCAB, n))


BASE = prose(220, 1)
ROWS = [(i, t, "en" if i % 2 else None, None if i % 3 else "s", len(t or "")) for i, t in enumerate(
    [None, "", " \n", BASE, BASE, BASE.replace(" ", "  ", 3) + " tail", prose(150, 2), "z" * 4000, prose(4000, 3), "card 4111111111111111 " + prose(80, 4)])]
ROWS += [ROWS[3], (None, BASE, "en", "s", 0), (None, None, None, None, None), (6, prose(90, 9), "en", "s", 0)]


@pytest.fixture(scope="module")
def docs(spark):
    df = spark.createDataFrame(ROWS, SCHEMA)
    return df.select("*", *[F.concat(F.lit(f"{c}-"), F.coalesce(F.col("doc_id").cast("string"), F.lit("null"))).alias(c) for c in CLASH]).coalesce(2)


@pytest.fixture(scope="module")
def empty(spark, docs):
    return spark.createDataFrame([], docs.schema)


@pytest.fixture(scope="module")
def bench(spark):
    return spark.createDataFrame([(1, BASE[:150]), (2, None), (None, "x y"), (4, "")], "item_id long, text string")


@pytest.fixture(scope="module")
def net(spark):
    make = lambda i: ("the of and " if i % 2 else "der die und ") * 30
    return language.fit(spark.createDataFrame([(i, make(i), "en" if i % 2 else "de") for i in range(40)], "doc_id long, text string, lang string"), epochs=2)


def toxic():
    return toxicity.train([("vile scum " * 3 + prose(40, i), 1) if i % 2 else (prose(40, i), 0) for i in range(40)], 0.5)


#: Operators that keep the columns of the rows, and those that have one row for each row of the input.
KEEP = {
    "quality": lambda d, b, n: quality.filter_documents(d), "neardup": lambda d, b, n: neardup.keep_one(d),
    "decontaminate": lambda d, b, n: decontaminate.clean(d, b), "private": lambda d, b, n: private.pseudonymize(d, key="k", count=None),
}
ONE = {
    "language": lambda d, b, n: language.predict(d, n), "toxicity": lambda d, b, n: toxicity.score(d, toxic()), "report": lambda d, b, n: decontaminate.report(d, b),
    "substrings": lambda d, b, n: substrings.removed(d), "classes": lambda d, b, n: neardup.classes(d),
    "judge": lambda d, b, n: quality.judge(d), "shards": lambda d, b, n: sharding.shard_documents(d),
}
MANY = {"licenses": lambda d, b, n: licenses.scan(d), "packing": lambda d, b, n: packing.pack_documents(d, TOKENIZER)}


@pytest.mark.parametrize("name", [*KEEP, *ONE, *MANY])
def test_odd_rows(docs, bench, net, name):
    out = (KEEP | ONE | MANY)[name](docs, bench, net)
    rows = out.collect()
    if name in KEEP:
        assert out.columns == docs.columns and all(r[c] == f"{c}-{'null' if r.doc_id is None else r.doc_id}" for r in rows for c in CLASH)
    if name in ONE:
        assert sorted(str(r.doc_id) for r in rows) == sorted(str(r[0]) for r in ROWS)
    if name == "neardup":
        assert sorted(str(r.doc_id) for r in rows) == ["0", "1", "2", "3", "6", "6", "7", "8", "9", "None", "None"]
    if name == "packing":
        assert {r.doc_id for r in rows} == {r[0] for r in ROWS}


@pytest.mark.parametrize("name", [*KEEP, *ONE, *MANY])
def test_empty_tables(empty, bench, net, name):
    assert (KEEP | ONE | MANY)[name](empty, bench, net).count() == 0


def test_an_id_that_repeats_loses_no_link(spark):
    other = prose(100, 77)
    rows = spark.createDataFrame([(3, BASE), (5, BASE + " word"), (3, other), (8, other + " end")], "doc_id long, text string")
    got = sorted(map(tuple, neardup.classes(rows).collect()))
    assert got == [(3, 3), (3, 3), (5, 3), (8, 3)]
    assert sorted(r.text for r in neardup.keep_one(rows).collect()) == sorted([BASE, other])


def plain_jaccard(a, b):
    grams = lambda t: [tuple(w[k:k + 5]) for w in [t.split()] for k in range(len(w) - 4)]
    x, y = ({g: grams(t).count(g) for g in set(grams(t))} for t in (a, b))
    return sum(1 / sum(max(x.get(o, 0) / x[g], y.get(o, 0) / y[g]) for o in set(x) | set(y)) for g in set(x) & set(y))


@pytest.mark.parametrize("block", [1024, 3])
def test_links_of_all_pairs(spark, block):
    rng = np.random.default_rng(6)
    texts = []
    for f in range(12):
        words = prose(120, 100 + f).split()
        for _ in range(7):
            own = list(words)
            for k in rng.integers(0, 120, rng.integers(0, 4)):
                own[k] = f"x{rng.integers(0, 99)}"
            texts.append(" ".join(own))
    up = list(range(len(texts)))
    links = [(i, j) for i, j in itertools.combinations(range(len(texts)), 2) if i // 7 == j // 7 and plain_jaccard(texts[i], texts[j]) >= 0.8]
    got = {r.doc_id: r.class_id for r in neardup._classes(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), block=block)[0].collect()}
    assert len(links) > 50 and np.mean([got[i] == got[j] for i, j in links]) >= 0.9
    for _ in up:
        for i, j in links:
            up[i] = up[j] = min(up[i], up[j])
    assert all(up[i] == up[got[i]] for i in got)


def feistel(value, key, kind, digits="0123456789", back=False):
    """The permutation of a string of digits, or its inverse, in plain Python."""
    half = len(value) // 2
    left, right = value[:half], value[half:]
    for k in (reversed(range(private.ROUNDS)) if back else range(private.ROUNDS)):
        target, other = (left, right) if k % 2 == 0 else (right, left)
        stream = hmac.new(key.encode(), f"{kind}|{k}|{other}".encode(), hashlib.sha256).hexdigest()
        steps = [int(stream[i * 4 % 60:i * 4 % 60 + 4], 16) for i in range(len(target))]
        moved = "".join(digits[(digits.index(c) + (-s if back else s)) % len(digits)] for c, s in zip(target, steps))
        left, right = (moved, right) if k % 2 == 0 else (left, moved)
    return left + right


def test_pseudonyms_are_a_permutation(spark):
    rows = spark.range(10_000).select(F.lpad(F.col("id").cast("string"), 4, "0").alias("v"))
    got = {r.v: r.p for r in rows.select("v", private.permuted(F.col("v"), "a key", "phone", (private.DIGITS,)).alias("p")).collect()}
    assert sorted(got.values()) == sorted(got)
    for v in list(got)[::97]:
        assert got[v] == feistel(v, "a key", "phone") and feistel(got[v], "a key", "phone", back=True) == v
    assert private.pseudonymize(spark.createDataFrame([(1, "call 020 7946 0958")], "doc_id long, text string"), key="a key").first().text == "call " + (lambda d: f"{d[:3]} {d[3:7]} {d[7:]}")(feistel("02079460958", "a key", "phone"))


def test_dates_are_a_permutation_of_real_dates(spark):
    days = spark.range(0, private.DAYS, 9).select(F.date_add(F.lit("1900-01-01").cast("date"), F.col("id").cast("int")).alias("d"))
    out = days.select("d", private._new_date(F.year("d"), F.month("d"), F.dayofmonth("d"), "k").alias("p"))
    row = out.agg(F.count("*").alias("n"), F.count_distinct("p").alias("k"), F.min(F.year("p")).alias("lo"), F.max(F.year("p")).alias("hi")).first()
    assert row.n == row.k and 1900 <= row.lo <= row.hi <= 2099


def test_network_against_loops_and_differences(net):
    """The convolution as loops over places, and its gradient by differences."""
    rng = np.random.default_rng(2)
    small = language.ByteNet(["a", "b", "c"], filters=3, dim=4, window=12)
    x, y = rng.integers(1, 256, (5, 12)).astype(np.uint8), rng.integers(0, 3, 5)
    plain = []
    for row in x:
        best = np.max([[sum(small.emb[row[at + k]] @ small.w[k, :, f] for k in range(small.span)) for f in range(9)] for at in range(12 - small.span + 1)], axis=0)
        plain.append(np.maximum(best + small.b, 0) @ small.v + small.c)
    assert np.allclose(small.logits(x), plain, atol=1e-4)
    loss = lambda: -np.mean(small.log_prob(x)[np.arange(5), y])
    for name in ("emb", "w", "b", "v", "c"):
        setattr(small, name, getattr(small, name).astype(np.float64))
    before = {p: getattr(small, p).copy() for p in ("emb", "w", "b", "v", "c")}
    moved = language.ByteNet(["a", "b", "c"], filters=3, dim=4, window=12)
    for p in before:
        setattr(moved, p, before[p].copy())
    moved.fit(x, y, epochs=1, batch=5, rate=1e-3)
    for p in ("v", "c", "b", "w", "emb"):
        flat = before[p].reshape(-1)
        for k in np.argsort(-np.abs((getattr(moved, p) - before[p]).reshape(-1)))[:3]:
            held = getattr(small, p).reshape(-1)
            held[k] = flat[k] + 1e-5
            up = loss()
            held[k] = flat[k] - 1e-5
            down = loss()
            held[k] = flat[k]
            # The first step of the running moments is the sign of the gradient.
            assert np.sign(getattr(moved, p).reshape(-1)[k] - flat[k]) == -np.sign(up - down)


def test_stages_and_chain(spark, tmp_path, docs, bench):
    docs.select("doc_id", "text", "lang", "source", "n_chars").write.parquet(str(tmp_path / "documents.parquet"))
    bench.write.parquet(str(tmp_path / "benchmark.parquet"))
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "near_duplicates", "decontamination", "pseudonyms", "best_fit_packing"]
    now, sizes = shared.documents(spark, str(tmp_path)), []
    for _, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, now, str(tmp_path))
        assert out.columns == now.columns
        now = shared.stored(out)
        sizes.append(sorted(str(r.doc_id) for r in now.collect()))
    assert sizes[0] == sorted(["3", "3", "4", "5", "6", "6", "8", "9", "None"][:9]) and sizes[1] == ["3", "6", "6", "8", "9", "None"] == sizes[2] == sizes[3]
    texts = {r.doc_id: r.text for r in now.collect()}
    assert BASE[:150] not in texts[3] and "4111111111111111" not in texts[9]
    packed = corpus_pipeline.run(spark, str(tmp_path)).collect()
    assert sorted({str(r.doc_id) for r in packed}) == sorted(set(sizes[3])) and sum(r.length for r in packed if r.piece == 0) > 0
