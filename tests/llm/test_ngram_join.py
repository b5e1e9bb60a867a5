import random
from collections import Counter, defaultdict

import numpy as np

from saferoute.llm import ngram_join as g

from . import helpers as h


def brute(rows):
    """doc_id -> (set size, component) by comparing all pairs that share a shingle."""
    sets, ids = [], []
    for i, t in rows:
        w = (t or "").lower().split() if (t or "").isascii() else (t or "").split()
        sets.append({tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set()))
        ids.append(i)
    lists, over, up = defaultdict(list), Counter(), list(range(len(sets)))
    for k, s in enumerate(sets):
        for x in s:
            lists[x].append(k)
    for own in lists.values():
        over.update((a, b) for n, b in enumerate(own) for a in own[:n])

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for (a, b), o in over.items():
        if 100 * o >= 80 * (len(sets[a]) + len(sets[b]) - o):
            up[root(a)] = root(b)
    least = {}
    for k, i in enumerate(ids):
        least[root(k)] = min(i, least.get(root(k), i))
    return {i: (len(s), least[root(k)]) for k, (i, s) in enumerate(zip(ids, sets, strict=True))}


def check(spark, texts):
    rows = list(enumerate(texts))
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in h.table(g.join(h.docs(spark, texts)))}
    assert got == brute(rows)
    return got


def edited(rng, words, n):
    out = list(words)
    for _ in range(n):
        out[rng.randrange(len(out))] = f"e{rng.randrange(10**6)}"
    return out


def corpus(seed, hub_copies):
    """Unrelated texts, exact copies, near copies of one text at and beyond the limit, chains, a shared passage."""
    rng = random.Random(seed)
    word = lambda: f"w{rng.randrange(5000)}"
    base = [[word() for _ in range(rng.randint(1, 120))] for _ in range(40)]
    hub = [word() for _ in range(90)]
    passage = [word() for _ in range(60)]
    texts = base + base[:8] + [edited(rng, hub, rng.randint(0, 5)) for _ in range(hub_copies)]
    texts += [[word() for _ in range(rng.randint(5, 40))] + passage + [word() for _ in range(rng.randint(5, 40))] for _ in range(25)]
    chain = [word() for _ in range(80)]
    for _ in range(12):
        texts.append(chain := edited(rng, chain, 1))
    texts += [[word() for _ in range(n)] for n in (1, 2, 3, 4, 5, 6, 7, 8, 9) for _ in range(2)]
    short = [word() for _ in range(9)]
    texts += [short, short[:-1], short[1:], [*short, "tail"]]
    rng.shuffle(texts)
    return [" ".join(t) for t in texts]


def test_components_equal_brute_force(spark):
    for seed in (1, 2):
        check(spark, corpus(seed, 60))


def test_long_lists_are_compared_in_blocks(spark, monkeypatch):
    monkeypatch.setattr(g, "SHORT", 3)
    monkeypatch.setattr(g, "BLOCK", 8)
    check(spark, corpus(3, 60))


def test_overlap_matrix():
    rng = np.random.default_rng(1)
    sets = [np.unique(rng.integers(0, 50, rng.integers(0, 20))) for _ in range(12)]
    a, b = sets[:5], sets[5:]
    pack = lambda x: (np.concatenate(x), np.array([len(s) for s in x]))
    want = [[len(np.intersect1d(s, t)) for t in b] for s in a]
    assert g.overlaps(*pack(a), *pack(b), width=7).tolist() == want


def test_awkward_rows(spark):
    rows = h.table(g.join(h.awkward(spark)))
    by = {(r["doc_id"], r["n_shingles"], r["component_id"]) for r in rows}
    assert len(rows) == 9 and (0, 0, 0) in by and (2, 0, 2) in by and (5, 7, 5) in by and (6, 7, 5) in by and (7, 1, 7) in by and (4, 1, 4) in by
    assert g.join(h.empty(spark)).count() == 0
    left = h.table(g.representatives(h.awkward(spark)))
    assert sorted(str(r["doc_id"]) for r in left) == ["0", "2", "3", "4", "5", "7", "None"]
    assert g.representatives(h.empty(spark)).count() == 0


def test_parts_dealt_in_two_steps(spark, monkeypatch):
    monkeypatch.setattr(g, "FAN", 2)
    monkeypatch.setattr(g, "PART_SIZE", 600)
    check(spark, corpus(5, 30))


def test_packed_sets():
    rng = np.random.default_rng(1)
    for a in (np.zeros(0, np.int64), np.array([-5]), np.array([-3, -1, 2**47, 2**62]), np.unique(rng.integers(-5, 2**50, 300))):
        assert (g.unpacked_set(g.packed_set(a)) == a).all() and len(g.unpacked_set(g.packed_set(a))) == len(a)


def test_one_row_of_each_group_stays_whatever_the_bitmap(spark, monkeypatch):
    texts = corpus(7, 40)
    rows = [(i % 90 if i % 7 else None, t, "en", "a", len(t)) for i, t in enumerate(texts)]
    docs = spark.createDataFrame(rows + rows[:20], h.DOCS)
    groups = brute(list(enumerate(texts)))
    for bits in (g.FILTER_BITS, 64):  # 64: nearly all rows are told apart by the join
        monkeypatch.setattr(g, "FILTER_BITS", bits)
        kept = [r["text"] for r in g.representatives(docs).collect()]
        at = {}
        for i, t in enumerate(texts):
            at.setdefault(groups[i][1], []).append(t)
        assert len(kept) == len(at) and sorted(sum(t in own for t in kept) for own in at.values()) == [1] * len(at)
