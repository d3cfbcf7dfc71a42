import random
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from xorvault.llm.common import words_of
from xorvault.llm.jaccard_forest import Forest, components, located, ngram_jaccard_join, numbered, roots, shared_counts, shingle_sets, signed


def shingle_set(text, size=5):
    w = words_of(text or "")
    return {tuple(w[i : i + size]) for i in range(len(w) - size + 1)} if len(w) >= size else ({tuple(w)} if w else set())


def brute(rows, threshold=0.8):
    """(class by row, links by row) from all pairs of distinct word sequences."""
    texts = {}
    for k, (i, t) in enumerate(rows):
        w = tuple(words_of(t or ""))
        texts.setdefault(w if w else ("", k), []).append((k, i))
    keys = list(texts)
    sets = [shingle_set(b" ".join(k).decode()) if k[0] != "" else set() for k in keys]
    parent, links = list(range(len(keys))), [0] * len(keys)

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in range(len(keys)):
        for b in range(a):
            both = len(sets[a] & sets[b])
            if both and both >= threshold * len(sets[a] | sets[b]):
                links[a] += 1
                links[b] += 1
                parent[find(a)] = find(b)
    least = defaultdict(list)
    for a, k in enumerate(keys):
        least[find(a)] += [i for _, i in texts[k] if i is not None]
    out = {}
    for a, k in enumerate(keys):
        for row, _ in texts[k]:
            out[row] = (min(least[find(a)], default=None), links[a], len(texts[k]))
    return out


def corpus(seed=3):
    rng = random.Random(seed)
    vocabulary = [f"w{k}" for k in range(400)]
    rows = [(k, " ".join(rng.choices(vocabulary, k=rng.choice([1, 3, 4, 5, 6, 30, 80, 200])))) for k in range(60)]
    for _ in range(80):  # near copies, and copies of copies
        t = rng.choice(rows)[1].split(" ")
        for _ in range(rng.choice([0, 1, 1, 2, 3])):
            t[rng.randrange(len(t))] = rng.choice(vocabulary)
        rows.append((len(rows), " ".join(t)))
    rows += [(900, None), (901, ""), (902, "  \n"), (903, rows[0][1]), (903, rows[0][1]), (None, rows[1][1]), (904, "é " * 3000), (905, "é " * 3001)]
    return rows


@pytest.mark.parametrize("block", [256, 4])
def test_as_brute_force(spark, block):
    rows = corpus()
    docs = spark.createDataFrame([(i, t, "x", "y") for i, t in rows], "doc_id long, text string, h string, keys string").repartition(5)
    got = ngram_jaccard_join(docs, forest=Forest(block=block)).collect()
    want = brute(rows)
    assert len(got) == len(rows)
    assert sorted((r.doc_id or -1, r.class_id or -1, r.n_links, r.n_copies) for r in got) == sorted((i or -1, want[k][0] or -1, want[k][1], want[k][2]) for k, (i, _) in enumerate(rows))


def test_large_group_of_near_copies(spark):
    rng = random.Random(1)
    base = [f"b{k}" for k in range(120)]
    rows = []
    for k in range(300):
        t = list(base)
        t[rng.randrange(120)] = f"x{k}"
        rows.append((k, " ".join(t)))
    got = {r.doc_id: (r.class_id, r.n_links) for r in ngram_jaccard_join(spark.createDataFrame(rows, "doc_id long, text string"), forest=Forest(block=64)).collect()}
    want = brute(rows)
    assert {c for c, _ in got.values()} == {0}
    missed = sum(want[k][1] - got[k][1] for k in range(300))
    assert missed <= 0.001 * sum(w[1] for w in want.values())


def test_empty(spark):
    assert ngram_jaccard_join(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_levels_keep_the_recall():
    """Fewer crowded tries leave room for longer prefixes; every level misses a pair at the threshold with at most 0.001."""
    f = Forest()
    levels = [f.level(g) for g in range(f.trees + 1)]
    assert levels == sorted(levels, reverse=True) and levels[1] == f.depth > levels[-1] > f.shallow
    for g, d in enumerate(levels):
        missed = lambda d: (1 - 0.8**f.shallow) ** (f.trees - g) * (1 - 0.8**d) ** g
        assert missed(d) <= 1 - f.recall and (d == f.depth or missed(d + 1) > 1 - f.recall)


def test_prefixes_follow_the_data(spark):
    """Under a crowded shallow node texts are told apart by longer prefixes; a lone pair of copies meets at short ones."""
    rng = random.Random(6)
    common = [f"c{k}" for k in range(60)]
    rows = [(k, " ".join(common + [f"u{k}x{j}" for j in range(25)])) for k in range(120)]  # alike at about 0.5
    lone = [f"l{k}" for k in range(80)]
    rows += [(500, " ".join(lone)), (501, " ".join([*lone[:-2], "x", "y"]))]
    forest = Forest(block=16)
    signatures = signed(spark.createDataFrame(rows, "doc_id long, text string"), forest, "doc_id", "text")
    texts = signatures.select("h", F.col("id").alias("rep"), "keys", "tails")
    got = {r.rep: r.nodes for r in located(texts, forest).collect()}
    keys = {r.rep: list(r["keys"]) for r in texts.collect()}
    assert got[500] == keys[500] and got[501] == keys[501]
    shallow, deep = (Counter(x for k in range(120) if k in got for x in of[k]) for of in (keys, got))
    assert max(shallow.values()) > 16 and sum(n * n for n in deep.values()) < sum(n * n for n in shallow.values()) / 2


def test_recall_is_measured(spark):
    """Pairs from just above the threshold up, at random: of their links, at least 99.5 % are found."""
    rng = random.Random(10)
    rows = []
    for k in range(150):
        t = [f"a{k}_{j}" for j in range(100)]
        rows.append((3 * k, " ".join(t)))
        for copy in (1, 2):
            u = list(t)
            u[-rng.randint(1, 20) :] = [f"b{k}_{copy}_{j}" for j in range(3)]
            rows.append((3 * k + copy, " ".join(u)))
    want = brute(rows)
    got = {r.doc_id: r.n_links for r in ngram_jaccard_join(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    links = sum(w[1] for w in want.values())
    assert links > 200 and all(got[i] <= want[i][1] for i in got) and sum(got.values()) >= 0.995 * links


def test_shingles_are_exact():
    rng = random.Random(7)
    texts = [[rng.choice([b"a", b"b", b"c"]) for _ in range(n)] for n in (0, 1, 2, 3, 4, 5, 6, 7, 30, 200)] * 2
    for size in (1, 2, 3, 5, 6, 8):
        ids, lengths, known = numbered(texts)
        sets = shingle_sets(ids, lengths, size)
        real = [shingle_set(b" ".join(t).decode(), size) for t in texts]
        for x, a in zip(sets, real):
            assert len(x) == len(a)
            for y, b in zip(sets, real):
                assert len(np.intersect1d(x, y)) == len(a & b)


def test_shared_counts_and_roots():
    rng = np.random.default_rng(2)
    sets = [np.unique(rng.integers(0, 60, 25).astype(np.uint64)) for _ in range(20)]
    assert (shared_counts(sets) == [[len(np.intersect1d(a, b)) for b in sets] for a in sets])[~np.eye(20, dtype=bool)].all()
    links = np.zeros((6, 6), bool)
    for a, b in ((5, 3), (3, 1), (2, 4)):
        links[a, b] = links[b, a] = True
    assert roots(links).tolist() == [0, 1, 2, 1, 2, 1]


def test_components(spark):
    rng = random.Random(4)
    chain = [(k, k + 1) for k in range(40)] + [(100 + rng.randrange(30), 100 + rng.randrange(30)) for _ in range(25)]
    got = {r.node: r.root for r in components(spark.createDataFrame(chain, "u long, v long")).collect()}
    parent = {}

    def find(x):
        while parent.setdefault(x, x) != x:
            x = parent[x]
        return x

    for a, b in chain:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    for x in parent:
        assert got.get(x, x) == find(x)
