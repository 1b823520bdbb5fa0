"""The quality rules against a plain numpy form of the same estimates, and their edge cases."""

import collections
import re

import numpy as np
import pytest

from starfold.llm import quality

SCHEMA = "doc_id long, text string, lang string, source string"
VOCAB = [f"{a}{b}{c}" for a in "bcdfg" for b in "aeiou" for c in ("n", "rt", "mple", "")]


def prose(n, seed):
    return " ".join(f"{w}{k}" for k, w in enumerate(np.random.default_rng(seed).choice(VOCAB, n)))


def statistics(t):
    w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
    grams = collections.Counter(zip(w, w[1:], w[2:]))
    rep = {k + j for k, g in enumerate(zip(w, w[1:], w[2:])) if grams[g] > 1 for j in range(3)}
    lines = [x for x in (t or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t or "")), len(lines) - len(set(lines)), len(rep)


def quantile(x, p=0.5):
    """The least value with at least this share of values at or below it."""
    x = np.sort(x)
    return x[max(0, int(np.ceil(p * len(x))) - 1)]


def brute(x):
    """Location, scatter and median distance of one group, by the same starts and steps."""
    floors = np.array(list(quality.FLOORS.values()))
    med = np.array([quantile(c) for c in x.T])
    s = np.sqrt((1.4826 * np.array([quantile(np.abs(c - m)) for c, m in zip(x.T, med)])) ** 2 + floors**2)
    z = (x - med) / s
    size = np.maximum(np.sqrt((z**2).sum(axis=1)), 1e-12)[:, None]
    t, u = np.tanh(z), z / size
    scatters = [np.eye(5), t.T @ t / len(x), 5 * u.T @ u / len(x)]
    ridge = np.diag(floors**2)
    d2 = lambda m, c: np.einsum("ij,jk,ik->i", x - m, np.linalg.inv(c), x - m)

    def step(m, c):
        d = d2(m, c)
        inner = x[d <= quantile(d) * (1 + 1e-12)]
        return inner.mean(axis=0), np.cov(inner.T, bias=True) + ridge

    found = []
    for k, c in enumerate(scatters):
        m, c = med, c * np.outer(s, s) + ridge
        for _ in range(2):
            m, c = step(m, c)
        found.append((np.linalg.slogdet(c)[1], k, m, c))
    _, _, m, c = min(found, key=lambda f: f[:2])
    for _ in range(100):
        was = np.linalg.slogdet(c)[1]
        m, c = step(m, c)
        if was - np.linalg.slogdet(c)[1] <= quality.REST:
            break
    return m, c, quantile(d2(m, c))


@pytest.fixture(scope="module")
def rows():
    rng = np.random.default_rng(4)
    out = []
    for i in range(260):
        n = int(np.clip(np.exp(rng.normal(5, 0.5)), 10, 800))
        t = prose(n, i) + " #" * int(rng.integers(0, 3)) + "\nline\nline" * int(rng.random() < 0.1)
        out.append((i, t, "en" if i % 5 else None, "a" if i % 7 else "b"))
    return [*out, (900, prose(200, 1) + " #$%" * 50, "en", "a"), (901, None, "en", "a"), (902, "", "de", "c"), (903, prose(90, 2) + "\n" + prose(30, 3) * 1, "xx", "z"), out[3]]


@pytest.fixture(scope="module")
def judged(spark, rows):
    return quality.judge(spark.createDataFrame(rows, SCHEMA)).collect()


def test_verdicts_equal_a_plain_form(judged, rows):
    got = {r.doc_id: r for r in judged}
    stats = {r[0]: statistics(r[1]) for r in rows}
    feats, failed = {}, {}
    for i, (n, chars, symbols, dup, rep) in stats.items():
        assert (got[i].n_words, got[i].word_chars, got[i].n_symbols, got[i].n_dup_lines, got[i].n_repeat_words) == stats[i]
        failed[i] = n < 50 or 100 * rep > 50 * n
        feats[i] = (np.log1p(n), chars / max(n, 1), np.sqrt(symbols / max(chars, 1)), np.log1p(dup) * 0.25, np.sqrt(rep / max(n, 1)))
        assert got[i].base_failed == failed[i]
    groups = collections.defaultdict(list)
    for i, _, lang, source in rows:
        if not failed[i]:
            groups[lang, source].append(feats[i])
            groups["all"].append(feats[i])
    models = {g: brute(np.array(x)) for g, x in groups.items() if len(x) >= 40}
    floors = np.array(list(quality.FLOORS.values()))
    for i, _, lang, source in rows:
        if failed[i]:
            assert not got[i].kept
            continue
        m, c, half = models.get((lang, source)) or models["all"]
        v = np.array(feats[i]) - m
        free = int((np.diag(np.linalg.cholesky(c)) > floors * 2**0.5).sum())
        median = quality.MEDIANS[free]
        d = v @ np.linalg.inv(c) @ v / (max(half / median, 1) if median else 1)
        assert abs(got[i].distance2 - d) <= 1e-6 * max(1, d) and got[i].kept == (d <= quality.CUTOFF)
    assert not got[900].kept and got[903].kept


def test_a_start_that_a_cluster_pulls_is_left(spark):
    """Two fifths of a group are junk of another kind: the half of least determinant is still the clean one."""
    rng = np.random.default_rng(2)
    clean = np.column_stack([rng.normal(5, 0.1, 300), rng.normal(5, 0.1, 300), *[np.zeros(300)] * 3])
    junk = np.column_stack([rng.normal(7, 0.4, 200), rng.normal(8, 0.5, 200), rng.normal(0.5, 0.1, 200), *[np.zeros(200)] * 2])
    points = spark.createDataFrame([("g", *map(float, r)) for r in np.vstack([clean, junk])], "grp string, " + ", ".join(f"{c} double" for c in quality.FEATURES))
    r = quality.estimates(points)[0].first()
    assert abs(r.m_f_len - 5) < 0.05 and abs(r.m_f_word - 5) < 0.05 and r.l_0_0 < 0.2 and r.n == 500


def test_many_groups_take_the_salted_join(spark):
    rows = spark.createDataFrame([(g, float(i), 0.0, 0.0, 0.0, 0.0) for i in range(5) for g in "ab"], "grp string, " + ", ".join(f"{c} double" for c in quality.FEATURES))
    small = spark.createDataFrame([("a", 1), ("c", 2)], "grp string, x int")
    both = [sorted(quality._meet(rows, small, sent, how="left").collect(), key=str) for sent in (True, False)]
    assert both[0] == both[1] and len(both[0]) == 10


def test_filter_keeps_rows_whole(spark, rows, judged):
    names = ["_row", "row", "grp", "kept", "n_words", "m_f_len", "d2"]
    df = spark.createDataFrame([(*r, *map(str, range(len(names)))) for r in rows], SCHEMA + "".join(f", {c} string" for c in names))
    kept = quality.filter_documents(df)
    assert kept.schema == df.schema
    want = {r.doc_id for r in judged if r.kept}
    plan = kept._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "CartesianProduct" not in plan and "SortMergeJoin" not in plan
    out = kept.collect()
    assert {r.doc_id for r in out} == want and all(r.m_f_len == "5" for r in out)
    assert sum(r.doc_id == 3 for r in out) == 2 * (3 in want)
    empty = spark.createDataFrame([], df.schema)
    assert quality.filter_documents(empty).count() == 0 == quality.judge(empty).count()
