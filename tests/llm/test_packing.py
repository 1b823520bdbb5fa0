"""The packing search and the tokenizer's short cut."""

import numpy as np
import public_tokenizers
import pytest

from starfold.llm import packing

PATH = public_tokenizers.path("word_bpe_49k.json")


def test_short_cut_equals_whole_texts():
    from tokenizers import Tokenizer

    tok, rng = Tokenizer.from_file(PATH), np.random.default_rng(5)
    letters = list("abcXYZ019 .,;:!?'\"-_()[]{}#*$%&|<>/\\@^`~\t\n\r\x0b\x0c  éÉßñ中文の한́​😀<s></s>[UNK]")
    texts = ["".join(rng.choice(letters, rng.integers(0, 40))) for _ in range(4000)]
    texts += ["x" * 5000, "ab.,!" * 300, "", "a" * 97 + " " + "b" * 96]
    got = packing.CachedTokenizer(PATH, limit=500).encode([t.encode() for t in texts])
    want = [np.array(e.ids, "<u4").tobytes() for e in tok.encode_batch(texts, add_special_tokens=False)]
    assert got == want


def test_long_chunks_do_not_stay_in_the_cache():
    tok = packing.CachedTokenizer(PATH)
    tok.encode([b"q" * 100_000 + b" short"])
    assert max(map(len, tok.cache)) <= tok.longest


def minimum(sizes, capacity):
    """Fewest bins, by trying every place for every piece."""
    best = len(sizes)

    def go(k, free):
        nonlocal best
        if len(free) >= best:
            return
        if k == len(sizes):
            best = len(free)
            return
        for j in range(len(free)):
            if free[j] >= sizes[k] and free[j] not in free[:j]:
                go(k + 1, [*free[:j], free[j] - sizes[k], *free[j + 1:]])
        go(k + 1, [*free, capacity - sizes[k]])

    go(0, [])
    return best


def check(bins, sizes, capacity):
    assert sorted(i for b in bins for i in b) == list(range(len(sizes)))
    assert all(sum(sizes[i] for i in b) <= capacity for b in bins)


@pytest.mark.parametrize("seed", range(40))
def test_search_against_every_packing(seed):
    rng = np.random.default_rng(seed)
    sizes = np.sort(rng.integers(3, 21, 9))[::-1].copy()
    first = packing.best_fit(sizes, 30)
    found = packing.local_search([list(b) for b in first], sizes, 30)
    check(found, sizes, 30)
    assert minimum(sizes.tolist(), 30) <= len(found) <= len(first)
    assert len(found) <= minimum(sizes.tolist(), 30) + 1


def test_every_exchange_raises_the_squared_fills():
    rng = np.random.default_rng(1)
    sizes = rng.integers(150, 440, 300)
    search = packing.Search(packing.best_fit(sizes, 1000), sizes, 1000)
    trade, seen = search._trade, []

    def watched(victim, give, other, take):
        fill = lambda: sum(sum(search.size[i] for i in b) ** 2 for b in search.bins)
        before = fill()
        trade(victim, give, other, take)
        seen.append((len(take), fill() - before))

    search._trade = watched
    check(search.run(), sizes, 1000)
    assert all(gain > 0 for _, gain in seen) and {1} <= {n for n, _ in seen}


@pytest.mark.parametrize("take", [0, 1, 2])
def test_each_kind_of_exchange(take):
    bins, sizes = {0: ([[0], [1]], [3, 5]), 1: ([[0], [1, 2]], [5, 4, 5]), 2: ([[0], [1, 2, 3]], [6, 3, 2, 4])}[take]
    search = packing.Search([list(b) for b in bins], np.array(sizes), 10)
    search._open([1])
    assert search._exchange(0)
    assert len(search.bins[0]) == (take if take else 0) and len(search.bins[1]) == len(bins[1]) + 1 - take


def test_repeated_and_drawn_pieces_end_near_the_bound():
    rng = np.random.default_rng(0)
    base = np.exp(rng.normal(5.9, 0.8, 10_000)).clip(60, 4096).astype(int)
    for sizes in (np.tile(base, 2)[:13_200], rng.choice(base, 12_500), rng.integers(2049, 4096, 2000)):
        found = packing.local_search(packing.best_fit(sizes, 4096), sizes, 4096)
        check(found, sizes, 4096)
        assert len(found) <= -(-int(sizes.sum()) // 4096) + 2 or sizes.min() > 2048


def test_idle_workers_drop_the_tokenizer(spark):
    """A worker keeps it from task to task, and gives it back once it rests."""
    import time

    from starfold.llm.shared import REST_S

    def held(batches):
        import pyarrow as pa

        from starfold.llm import packing

        for _ in batches:
            pass
        yield pa.RecordBatch.from_pydict({"n": [packing.worker_tokenizer.cache_info().currsize]})

    docs = spark.range(8, numPartitions=4).selectExpr("id as doc_id", "concat('some text ', id) as text")
    assert packing.tokenized_pieces(docs, PATH).count() == 8
    look = lambda: sum(r.n for r in docs.select("doc_id").mapInArrow(held, "n bigint").collect())
    assert look() > 0
    time.sleep(REST_S + 1.5)
    assert look() == 0
