"""Hashes of word shingles for many texts at once, in numpy."""

from __future__ import annotations

import numpy as np

from starfold.llm.shared import WORD_BYTES

U = np.uint64
with np.errstate(over="ignore"):
    BYTE = np.random.default_rng(11).integers(1, 1 << 63, 256, dtype=np.uint64) * U(2) + U(1)
PLACE = U(0x9E3779B97F4A7C15)
STEP = np.random.default_rng(13).integers(1, 1 << 63, 16, dtype=np.uint64) * U(2) + U(1)


def mix(z: np.ndarray) -> np.ndarray:
    z = (z ^ (z >> U(30))) * U(0xBF58476D1CE4E5B9)
    z = (z ^ (z >> U(27))) * U(0x94D049BB133111EB)
    return z ^ (z >> U(31))


def word_hashes(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Hash of every word of every text, in order, and the number of its text."""
    data = np.frombuffer(b" ".join(t.translate(WORD_BYTES) for t in texts) + b" ", np.uint8)
    word = data != 32
    edge = np.flatnonzero(np.diff(np.concatenate(([False], word)).astype(np.int8)))
    starts, ends = edge[::2], edge[1::2]
    if not len(starts):
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    sizes = ends - starts
    offsets = np.cumsum(sizes) - sizes
    within = np.arange(int(sizes.sum())) - np.repeat(offsets, sizes)
    power = np.cumprod(np.full(int(sizes.max()), PLACE, np.uint64))
    sums = np.add.reduceat(BYTE[data[word]] * power[within], offsets)
    bounds = np.cumsum([len(t) + 1 for t in texts])
    return mix(sums + sizes.astype(np.uint64)), np.searchsorted(bounds, starts, side="right")


def shingle_hashes(texts: list[bytes], words: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Hash of each run of ``words`` words and the number of its text; a shorter text that has a word is one shingle."""
    h, doc = word_hashes(texts)
    n = len(h)
    counts = np.bincount(doc, minlength=len(texts)) if n else np.zeros(len(texts), np.int64)
    out, own = np.zeros(0, np.uint64), np.zeros(0, np.int64)
    if n >= words:
        acc = np.zeros(n - words + 1, np.uint64)
        for i in range(words):
            acc += h[i:n - words + 1 + i] * STEP[i]
        same = doc[:n - words + 1] == doc[words - 1:]
        out, own = mix(acc[same]), doc[:n - words + 1][same]
    few = np.flatnonzero((counts > 0) & (counts < words))
    if len(few):
        first = np.searchsorted(doc, few)
        extra = np.array([int(mix(np.array([(h[a:a + counts[k]] * STEP[:counts[k]]).sum() + U(int(counts[k]))], np.uint64))[0]) for k, a in zip(few, first)], np.uint64)
        out, own = np.concatenate((out, extra)), np.concatenate((own, few))
        order = np.argsort(own, kind="stable")
        out, own = out[order], own[order]
    return out, own


def weighted(hashes: np.ndarray, owner: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct 48-bit elements of each text, their text and their weight. At most 65,536 texts."""
    key = np.sort((owner.astype(np.uint64) << U(48)) | (hashes >> U(16)))
    if not len(key):
        return key, owner, np.zeros(0)
    at = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
    weight = np.diff(np.concatenate((at, [len(key)]))).astype(float)
    key = key[at]
    return key & U((1 << 48) - 1), (key >> U(48)).astype(np.int64), weight


def signatures(element: np.ndarray, owner: np.ndarray, weight: np.ndarray, texts: int, registers: int) -> np.ndarray:
    """ProbMinHash: each element's arrivals are a Poisson process of its weight, each arrival falls on a random
    register, and a register names the element that came first. An element stops once it is later than every
    register of its text."""
    first = np.full((texts, registers), np.inf)
    name = np.zeros((texts, registers), np.uint64)
    flat, who = first.reshape(-1), name.reshape(-1)
    e, d, w = element, owner, weight
    t = np.zeros(len(e))
    k = 0
    while len(e):
        r = mix(e * U(0xD6E8FEB86659FD93) + U((k * 0x9E3779B97F4A7C15 + 1) & ((1 << 64) - 1)))
        t = t - np.log(((r >> U(11)).astype(float) + 0.5) / float(1 << 53)) / w
        slot = d * registers + (mix(r) % U(registers)).astype(np.int64)
        won = np.flatnonzero(t < flat[slot])
        won = won[np.argsort(-t[won], kind="stable")]
        flat[slot[won]] = t[won]
        who[slot[won]] = e[won]
        live = t < first.max(axis=1)[d]
        e, d, w, t = e[live], d[live], w[live], t[live]
        k += 1
    return name


def probability_jaccard(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> float:
    """Exact probability Jaccard of two weighted sets (sorted distinct elements, weights)."""
    common, i, j = np.intersect1d(a[0], b[0], assume_unique=True, return_indices=True)
    if not len(common):
        return 0.0
    x, y = a[1], b[1]
    only_x, only_y = x.sum() - x[i].sum(), y.sum() - y[j].sum()
    x, y = x[i], y[j]
    ratio = y / x
    order = np.argsort(ratio, kind="stable")
    x, y, ratio = x[order], y[order], ratio[order]
    upto = np.searchsorted(ratio, ratio, side="right")
    below = np.concatenate(([0.0], np.cumsum(x)))[upto] + only_x
    above = y.sum() - np.concatenate(([0.0], np.cumsum(y)))[upto] + only_y
    return float((1 / (below / x + above / y)).sum())


def probability_jaccards(texts: list[bytes], a: np.ndarray, b: np.ndarray, words: int = 5) -> np.ndarray:
    """Exact probability Jaccard of texts ``a[k]`` and ``b[k]`` for every pair k; each text is hashed once."""
    h, own = shingle_hashes(texts, words)
    if not len(h):
        return np.zeros(len(a))
    order = np.lexsort((h, own))
    h, own = h[order], own[order]
    at = np.flatnonzero(np.concatenate(([True], (h[1:] != h[:-1]) | (own[1:] != own[:-1]))))
    weight = np.diff(np.concatenate((at, [len(h)]))).astype(float)
    own, element = own[at], np.unique(h[at], return_inverse=True)[1]
    cut = np.searchsorted(own, np.arange(len(texts) + 1))
    total = np.bincount(own, weights=weight, minlength=len(texts))
    span = int(element.max()) + 1
    key = own * span + element
    sizes = np.diff(cut)
    swap = sizes[a] > sizes[b]
    a, b = np.where(swap, b, a), np.where(swap, a, b)
    # Every element of the text with fewer of them is looked up in the other.
    n = sizes[a]
    pair = np.repeat(np.arange(len(a)), n)
    left = np.arange(len(pair)) + np.repeat(cut[a] - (np.cumsum(n) - n), n)
    want = b[pair] * span + element[left]
    right = np.minimum(np.searchsorted(key, want), len(key) - 1)
    hit = key[right] == want
    pair, x, y = pair[hit], weight[left[hit]], weight[right[hit]]
    if not len(pair):
        return np.zeros(len(a))
    ratio = y / x
    order = np.lexsort((ratio, pair))
    pair, x, y, ratio = pair[order], x[order], y[order], ratio[order]
    ends = np.flatnonzero(np.concatenate(((pair[1:] != pair[:-1]) | (ratio[1:] != ratio[:-1]), [True]))) + 1
    upto = np.repeat(ends, np.diff(np.concatenate(([0], ends))))
    # Weights are counts, so running sums over all pairs are exact.
    run_x, run_y = np.concatenate(([0.0], np.cumsum(x))), np.concatenate(([0.0], np.cumsum(y)))
    edge = np.searchsorted(pair, np.arange(len(a) + 1))
    lo, hi = edge[pair], edge[pair + 1]
    below = run_x[upto] - run_x[lo] + total[a][pair] - (run_x[hi] - run_x[lo])
    above = run_y[hi] - run_y[upto] + total[b][pair] - (run_y[hi] - run_y[lo])
    return np.bincount(pair, weights=1 / (below / x + above / y), minlength=len(a))
