import math
import random
import re
import tracemalloc
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from xorvault.llm import queries
from xorvault.llm.decontaminate import ItemIndex, Match, Words, densest, find_contamination, without_contaminated
from xorvault.llm.linear import isotonic, platt
from xorvault.llm.common import words_of
from xorvault.llm.compression_rules import quality_rules
from xorvault.llm.pair_index_bpe import encode_documents
from xorvault.llm.quality_svm import Forms, fit_hinge, fit_quality, form, key, ngrams, score_quality
from xorvault.llm.secret_guess import scan_secrets
from xorvault.llm.token_counts import PretokenTrie, count_tokens, default_ranks, loaded, piece_scores
from xorvault.llm.toxicity_knn import PARTS, BlockMaxIndex, built_index, fit_toxicity, score_toxicity, terms_of_word

# --- Token counts


def viterbi(data, scores):
    best = [(0.0, 0)]
    for end in range(1, len(data) + 1):
        best.append(max(((best[k][0] + scores[data[k:end]], -(best[k][1] + 1)) for k in range(end) if data[k:end] in scores)))
        best[-1] = (best[-1][0], -best[-1][1])
    return best[-1]


@pytest.mark.parametrize("text", ["", "hello world", "internationalization", "ééé 漢字😀", "a" * 60, "foo_bar(baz)  qux\n\n"])
def test_trie_is_viterbi(text):
    trie = loaded(default_ranks())
    (got,) = trie.count([text])
    want = [viterbi(w.encode(), trie.scores) for w in trie.find(text)]
    assert got["n_tokens"] == sum(c for _, c in want)
    assert got["log_score"] == pytest.approx(sum(s for s, _ in want))


def test_trie_shares_prefixes():
    trie = PretokenTrie(piece_scores(default_ranks()))
    trie.count(["abcdef"])
    n = len(trie.nodes)
    trie.count(["abcdeg"])
    assert len(trie.nodes) == n + 1


def test_very_long_words():
    """Words of a million letters take bounded memory; beyond the stored prefix the result is still Viterbi's."""
    rng = random.Random(5)
    trie = PretokenTrie(piece_scores(default_ranks()))
    for size in (63, 64, 65, 200, 9000):
        word = "".join(rng.choices("etaoinshrdlu", k=size))
        (got,) = trie.count([word])
        score, n = viterbi(word.encode(), trie.scores) if size < 1000 else window_viterbi(word.encode(), trie.scores)
        assert got["n_tokens"] == n and got["log_score"] == pytest.approx(score)
    tracemalloc.start()
    trie.count(["a" * 200_000, "".join(rng.choices("etaoinshrdlu", k=200_000))])
    _, peak = tracemalloc.get_traced_memory()
    tracemalloc.stop()
    assert peak < 5 << 20 and len(trie.nodes) <= 7 * 64 and max(map(len, trie.terminal)) <= 64


def window_viterbi(data, scores):
    longest = max(map(len, scores))
    best = [(0.0, 0)]
    for end in range(1, len(data) + 1):
        best.append(max((best[k][0] + scores[data[k:end]], best[k][1] - 1) for k in range(max(0, end - longest), end) if data[k:end] in scores))
    return best[-1][0], -best[-1][1]


def test_token_rows(spark):
    docs = spark.createDataFrame([(1, None, 7), (2, "", 7), (3, "a b", 7), (3, "a b", 7)], "doc_id long, text string, n_tokens int")
    assert [(r.doc_id, r.n_tokens) for r in count_tokens(docs).collect()] == [(1, 0), (2, 0), (3, 2), (3, 2)]
    assert count_tokens(docs.limit(0)).count() == 0


# --- Quality


def labelled(spark, n=400):
    rng = random.Random(1)
    prose = lambda: " ".join(rng.choice("river stone quiet morning walks under bright leaves with old friends".split()) for _ in range(60)) + "."
    junk = lambda: " ".join(rng.choice(["BUY!!", "CLICK!!", "$$$", "win***"]) for _ in range(60))
    rows = [(k, prose() if k % 3 else junk(), int(bool(k % 3))) for k in range(n)]
    return rows, spark.createDataFrame([(i, t) for i, t, _ in rows], "doc_id long, text string"), spark.createDataFrame([(i, q, None) for i, _, q in rows], "doc_id long, quality int, toxic int")


def test_quality(spark):
    rows, docs, labels = labelled(spark)
    got = {r.doc_id: r for r in score_quality(docs, labels).collect()}
    truth = {i: q for i, _, q in rows}
    held = [i for i in truth if zlib.crc32(str(i).encode()) % 4 == 2]
    assert held and all(got[i].held_out for i in held)
    assert all(got[i].predicted == truth[i] for i in held)
    flipped = labels.selectExpr("doc_id", "CASE WHEN crc32(cast(cast(doc_id AS string) AS binary)) % 4 = 2 THEN 1 - quality ELSE quality END AS quality")
    assert {r.doc_id: r.score for r in score_quality(docs, flipped).collect()} == {i: r.score for i, r in got.items()}  # held-out labels are never read


def test_quality_edges(spark):
    _, docs, labels = labelled(spark, 60)
    odd = docs.unionAll(spark.createDataFrame([(None, "x"), (900, None), (901, "")], "doc_id long, text string"))
    got = score_quality(odd, labels).collect()
    assert len(got) == 63 and all(0 <= r.score <= 1 for r in got)
    assert score_quality(odd, labels.limit(0)).count() == 63
    assert score_quality(odd.limit(0), labels).count() == 0


def test_hinge_is_solved():
    """The dual solution's duality gap is small on random data."""
    rng = np.random.default_rng(0)
    x, y = rng.normal(size=(80, 5)), np.sign(rng.normal(size=80))
    cost = np.full(80, 0.5)
    w = fit_hinge([np.arange(5)] * 80, list(x), y, 5, cost, rounds=3000)
    primal = 0.5 * w @ w + (cost * np.maximum(0, 1 - y * (x @ w))).sum()
    for _ in range(20):
        v = w + rng.normal(size=5) * 0.05
        assert 0.5 * v @ v + (cost * np.maximum(0, 1 - y * (x @ v))).sum() >= primal - 1e-3


def test_calibrations():
    m = np.array([-2.0, -1, -1, 0, 1, 1, 2, 3])
    a, b = platt(m, np.array([0, 0, 0, 0, 1, 1, 1, 1]))
    assert a > 0 and 1 / (1 + np.exp(-(a * 2 + b))) > 0.5 > 1 / (1 + np.exp(-(a * -2 + b)))
    x, level = isotonic(np.array([0.1, 0.2, 0.3, 0.4]), np.array([0.0, 1, 0, 1]), weight=0)
    assert (np.diff(level) >= 0).all() and level[1] == pytest.approx(0.5)


# --- Toxicity


def test_nearest_is_exact():
    rng = np.random.default_rng(3)
    idf = rng.uniform(0.5, 3, 12)
    index = BlockMaxIndex(12, list(range(500)), np.zeros(500, np.int64), idf, block=16)
    vectors = [index.vector({int(t): int(rng.integers(1, 4)) for t in rng.choice(12, rng.integers(1, 5), replace=False)}) for _ in range(500)]
    index.add(vectors)
    dense = np.zeros((500, 12))
    for j, (t, w) in enumerate(vectors):
        dense[j, t] = w
    for trial in range(60):
        t, w = index.vector({int(t): int(rng.integers(1, 4)) for t in rng.choice(12, rng.integers(1, 5), replace=False)})
        without = -1 if trial % 2 else trial
        score = np.round(dense[:, t] @ w, 12)
        if without >= 0:
            score[without] = 0
        want = [j for j in np.lexsort((np.arange(500), -score)) if score[j] > 0][:15]
        got, cosine = index.nearest(t, w, 15, without)
        assert np.allclose(cosine, score[want], atol=1e-9)
        assert got.tolist() == want


def test_toxicity(spark):
    rng = random.Random(2)
    calm = "the quiet river runs past old stones under a wide pale sky and birds rest".split()
    rows = []
    for k in range(600):
        w = rng.choices(calm, k=80)
        if k % 5 == 0:
            for _ in range(4):
                w[rng.randrange(80)] = rng.choice(["vilewretch", "foulbeast", "nastyfool"])
        rows.append((k, " ".join(w), int(k % 5 == 0)))
    docs = spark.createDataFrame([(i, t) for i, t, _ in rows] + [(9000, None), (9001, "")], "doc_id long, text string")
    labels = spark.createDataFrame([(i, y) for i, _, y in rows], "doc_id long, toxic int")
    got = {r.doc_id: r for r in score_toxicity(docs, labels).collect()}
    held = [(i, y) for i, _, y in rows if zlib.crc32(str(i).encode()) % 5 == 0]
    assert all(got[i].held_out and got[i].predicted == y for i, y in held)
    assert got[9000].predicted == 0 == got[9001].predicted and got[0].neighbours and got[0].shared_terms
    assert score_toxicity(docs, labels.limit(0)).count() == len(rows) + 2


def test_toxicity_as_brute_force(spark):
    """Terms by their chi-square, document frequencies, cosines over dense vectors, votes, and calibration without each part."""
    rng = random.Random(12)
    calm = "the quiet river runs past old stones under a wide pale sky and birds rest".split()
    bad = ["vilewretch", "foulbeast", "nastyfool", "vilewretches"]
    rows = []
    for k in range(500):
        w = rng.choices(calm, k=rng.randint(20, 60))
        toxic = int(k % 4 == 0)
        for _ in range(rng.randint(1, 4) if toxic else int(rng.random() < 0.05)):
            w[rng.randrange(len(w))] = rng.choice(bad)
        rows.append((k, " ".join(w), toxic))
    docs = spark.createDataFrame([(i, t) for i, t, _ in rows], "doc_id long, text string")
    labels = spark.createDataFrame([(i, y) for i, _, y in rows], "doc_id long, toxic int")
    part = {r.doc_id: r.p for r in docs.selectExpr("doc_id", f"pmod(xxhash64(doc_id), {PARTS}) AS p").collect()}
    examples = [(i, t, y) for i, t, y in rows if zlib.crc32(str(i).encode()) % 5 != 0]
    words = {i: t.split() for i, t, _ in rows}
    terms_of = {i: {t for w in words[i] for t in terms_of_word(w.encode())} for i in words}

    def strong(of):
        p, n = sum(y for *_, y in of), sum(1 - y for *_, y in of)
        out = []
        for t in set().union(*(terms_of[i] for i, *_ in of)):
            a, b = sum(y for i, _, y in of if t in terms_of[i]), sum(1 - y for i, _, y in of if t in terms_of[i])
            if a + b >= 4 and a * n > b * p:
                table = np.array([[a, b], [p - a, n - b]], float)
                want = table.sum(1, keepdims=True) @ table.sum(0, keepdims=True) / table.sum()
                if (x := (((table - want) ** 2) / want).sum()) >= 30:
                    out.append((x, t))
        kept = []
        for _, t in sorted(out, key=lambda x: (-round(x[0], 9), x[1])):
            stem = t.rstrip(b"-")
            if not any(stem.startswith(u.rstrip(b"-")) or u.startswith(stem) for u in kept):
                kept.append(t)
        return sorted(kept)

    def dense(terms, i):
        idf = [math.log((1 + len(rows)) / (1 + sum(t in terms_of[j] for j in terms_of))) + 1 for t in terms]
        hits = [[t for t in terms_of_word(w.encode()) if t in terms] for w in words[i]]
        count = Counter(t for h in hits for t in h)
        v = np.array([(1 + math.log(count[t])) * x if count[t] else 0.0 for t, x in zip(terms, idf)] + [1 + math.log(rest) if (rest := sum(not h for h in hits)) else 0.0])
        return count, v / (np.linalg.norm(v) or 1.0)

    def share(i, terms, order, truth):
        count, v = dense(terms, i)
        if not count:
            return None
        cosine = np.round(np.array([dense(terms, j)[1] @ v for j in order]), 12)
        near = [j for j in np.lexsort((np.arange(len(order)), -cosine))[:15] if cosine[j] > 0]
        return sum(cosine[j] * truth[order[j]] for j in near) / (sum(cosine[j] for j in near) + 0.25)

    model = fit_toxicity(docs, labels)
    truth = {i: y for i, _, y in rows}
    assert model.terms == strong(examples) and len(model.terms) >= 3
    order = [int(i) for i in model.index.ids]
    assert sorted(order) == [i for i, *_ in examples]
    got = {r.doc_id: r for r in score_toxicity(docs, labels).collect()}
    for i in range(0, 500, 7):
        x = share(i, model.terms, order, truth)
        assert got[i].score == pytest.approx(model.bare if x is None else float(np.interp(x, model.knots, model.levels)), abs=1e-6)
        assert x is None or len(got[i].neighbours.split(",")) == 15
    shares, seen, bare = [], [], []
    for k in range(PARTS):
        rest = [x for x in examples if part[x[0]] != k]
        terms = strong(rest)
        index, _ = built_index(terms, [(str(i), y, {}) for i, _, y in rest], np.ones(len(terms)))
        for i, _, y in (x for x in examples if part[x[0]] == k):
            x = share(i, terms, [int(j) for j in index.ids], truth)
            (bare if x is None else seen).append(y)
            shares += [] if x is None else [x]
    assert model.bare == pytest.approx((sum(bare) + 0.5) / (len(bare) + 2))
    knots, levels = isotonic(np.array(shares), np.array(seen, float), prior=float(np.mean(seen)))
    at = np.linspace(0, 1, 50)
    assert np.interp(at, model.knots, model.levels) == pytest.approx(np.interp(at, knots, levels), abs=1e-6)


def test_quality_as_brute_force(spark):
    """Scores are the calibrated margin over a text's known features; ratios are smoothed log ratios of class frequencies."""
    rows, docs, labels = labelled(spark, 240)
    model = fit_quality(docs, labels)
    at = {int(k): j for j, k in enumerate(model.keys)}
    forms = Forms()
    features = {i: {at[x] for g in ngrams(words_of(t), forms) if (x := key(g)) in at} for i, t, _ in rows}
    got = {r.doc_id: r.score for r in score_quality(docs, labels).collect()}
    for i in features:
        f = sorted(features[i])
        margin = float(model.ratio[f] @ model.weight[f]) / (float(np.linalg.norm(model.ratio[f])) or 1.0) + model.bias
        assert got[i] == pytest.approx(1 / (1 + math.exp(-max(-30, min(30, model.a * margin + model.b)))), abs=1e-9)
    train = [(i, y) for i, _, y in rows if zlib.crc32(str(i).encode()) % 4 != 2]
    for y, side in ((1, 1), (0, -1)):
        assert any(side * r > 0.5 for r in model.ratio)
    j = at[key((b"BUY!!",))]
    pos, neg = (sum(j in features[i] for i, t in train if t == y) for y in (1, 0))
    n_pos, n_neg = (sum(t == y for _, t in train) for y in (1, 0))
    assert model.ratio[j] == pytest.approx(math.log((1 + pos) / (2 + n_pos)) - math.log((1 + neg) / (2 + n_neg)))


def test_forms_are_whole():
    """A word's form goes to its end, however long."""
    assert form(b"a1" * 20) == "a0" * 20 and form(b"a1" * 20 + b"!") != form(b"a1" * 20 + b"?")
    assert len(form(b"aB3-" * 250_000)) == 1_000_000


ROWS = [(1, None), (2, ""), (3, "plain words here"), (3, "plain words here"), (None, "plain words here"), (None, None), (4, "x" * 300_000), (5, "word " * 60_000)]


@pytest.mark.parametrize("name", ["tokens", "quality", "toxicity", "rules", "secrets", "bpe", "leaks"])
def test_odd_rows(spark, name):
    """Null and repeated ids and texts, very long words and texts, and columns with the names that operators use."""
    docs = spark.createDataFrame([(i, t, 1, "k") for i, t in ROWS], "doc_id long, text string, score int, _r string")
    labels = spark.createDataFrame([(3, 1, 0, "x"), (3, 1, 0, "x"), (None, 0, 1, "x"), (2, None, None, "x")], "doc_id long, quality int, toxic int, text string")
    items = spark.createDataFrame([(1, "plain words here", 1), (1, "plain words here", 1), (None, None, 1)], "item_id long, text string, doc_id int")
    run = {
        "tokens": lambda d: count_tokens(d), "quality": lambda d: score_quality(d, labels), "toxicity": lambda d: score_toxicity(d, labels),
        "rules": lambda d: quality_rules(d), "secrets": lambda d: scan_secrets(d), "bpe": lambda d: encode_documents(d), "leaks": lambda d: find_contamination(d, items),
    }[name]
    got = [tuple(r) for r in run(docs).collect()]
    if name == "leaks":
        assert sorted(map(str, (r[:2] for r in got))) == sorted(["(3, 1)", "(3, 1)", "(None, 1)"])
    else:
        assert sorted(str(r[0]) for r in got) == sorted(str(i) for i, _ in ROWS)
        assert len({repr(r[1:]) for r in got if r[0] == 3}) == 1
    assert run(docs.limit(0)).count() == 0


# --- Decontamination

ITEMS = [(1, "Where does the silver river of the northern vale begin its run? It starts at the high glacier of Morn."), (2, "Name the colour of copper salts in flame. The flame turns green."), (3, None), (4, ""), (5, " ".join(f"long{k}" for k in range(300)) + ". The end is here.")]


def test_leaks(spark):
    rng = random.Random(5)
    filler = lambda n: " ".join("".join(rng.choices("abcdefgh", k=rng.randint(2, 7))) for _ in range(n))
    rows = [(1, filler(90) + " " + ITEMS[0][1] + " " + filler(200)), (2, filler(300)), (3, ITEMS[1][1].upper()), (4, None), (5, ""), (6, filler(45) + " " + ITEMS[4][1]), (7, "Where does the silver river of the northern vale begin its run? " + filler(60)), (3, ITEMS[1][1])]
    docs = spark.createDataFrame([(i, t, 0.5) for i, t in rows], "doc_id long, text string, score double")
    items = spark.createDataFrame(ITEMS, "item_id long, text string")
    got = sorted((r.doc_id, r.item_id) for r in find_contamination(docs, items).collect())
    assert got == [(1, 1), (3, 2), (3, 2), (6, 5)]
    assert sorted((r.doc_id, r.item_id) for r in find_contamination(docs, items, match=Match(shard_items=1, shards_per_scan=2)).collect()) == got
    assert find_contamination(docs, items.limit(0)).count() == 0 and find_contamination(docs.limit(0), items).count() == 0
    for match in (Match(), Match(shard_items=1, shards_per_scan=2)):
        clean = without_contaminated(docs.withColumn("_items", F.lit(3)), items, match=match)
        assert clean.columns == [*docs.columns, "_items"] and sorted(r.doc_id for r in clean.collect()) == [2, 4, 5, 7]


def test_answers_must_be_at_the_question(spark):
    """The words of a question's answer strewn over a long text are no leak; the answer some words after the question is."""
    rng = random.Random(15)
    filler = lambda n: " ".join("".join(rng.choices("mnopqr", k=rng.randint(2, 7))) for _ in range(n))
    question, answer = "Where does the silver river of the northern vale begin its run?", "It starts at the high glacier of Morn."
    strewn = question + " " + " ".join(filler(130) + " " + w for w in answer.split())
    rows = [(1, strewn), (2, filler(300) + " " + question + " Answer, in short: " + answer + filler(300)), (3, answer + " " + filler(10) + " " + question)]
    got = [r.doc_id for r in find_contamination(spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame([(1, f"{question} {answer}")], "item_id long, text string")).collect()]
    assert sorted(got) == [2, 3]


def brute_leaks(docs, items, match=Match()):
    """(doc, item) pairs by scoring every piece for every pair of halves, and looking at every window."""
    items = sorted({(i, t) for i, t in items if t and re.findall(r"\w+", t)}, key=lambda x: (str(x[0]), x[1]))
    split = lambda s: re.findall(r"\w+", s.lower())
    pieces = []
    for j, (_, t) in enumerate(items):
        w = split(t)
        size = math.ceil(len(w) / math.ceil(len(w) / (match.half * 3 // 2)))
        pieces += [(j, w[k : k + size]) for k in range(0, len(w), size)]
    mean = sum(len(p) for _, p in pieces) / max(1, len(pieces))
    df = Counter(t for _, p in pieces for t in set(p))
    vocabulary = {w for _, t in items for w in split(t)}
    weight = lambda t, p: math.log(1 + (len(pieces) - df[t] + 0.5) / (df[t] + 0.5)) * p.count(t) * (match.k1 + 1) / (p.count(t) + match.k1 * (1 - match.b + match.b * len(p) / mean))
    weights = [(j, {t: weight(t, p) for t in set(p)}) for j, p in pieces]
    out = []
    for i, text in docs:
        w = [x if x in vocabulary else None for x in split(text or "")]
        found = set()
        for h in range(0, len(w), match.half):
            query = set(w[h : h + 2 * match.half])
            found |= {j for j, p in weights if sum(v for t, v in p.items() if t in query) >= match.least_share * sum(p.values())}
        for j in found:
            s = [x for x in re.split(r"(?<=[.!?])\s+", items[j][1].strip()) if re.search(r"\w", x)]
            q, a = (split(" ".join(s[:-1])) if len(s) > 1 else split(items[j][1])), split(s[-1])
            n = min(3, len(q))
            grams = lambda x: [tuple(x[k : k + n]) for k in range(len(x) - n + 1)]
            own, seen, width = set(grams(q)), grams(w), 3 * (len(q) + len(a)) // 2 + match.half
            best, start = max(((len(own & set(seen[k : k + width])), -k) for k in range(len(seen)) if seen[k] in own), default=(0, 0))
            near = set(w[max(0, -start - len(a) - match.half) : -start + width + len(a) + match.half])
            if best >= match.question_overlap * len(own) and sum(t in near for t in a) >= match.answer_overlap * len(a):
                out.append((i, items[j][0]))
    return out


def test_leaks_as_brute_force(spark, sf_dir):
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()]
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf_dir}/benchmark.parquet").collect()]
    got = sorted((r.doc_id, r.item_id) for r in queries.op10_bm25_decontamination(spark, sf_dir).collect())
    assert got == sorted(brute_leaks(docs, items)) and got
    assert {(i, j) for i, t in docs for j, x in items if x and x in (t or "")} <= set(got)


def test_densest():
    rng = random.Random(4)
    for _ in range(200):
        hits = [(rng.randrange(60), rng.choice("abcdef")) for _ in range(rng.randint(0, 25))]
        start, count = densest(hits, 9)
        each = {p: len({g for q, g in hits if p <= q < p + 9}) for p, _ in hits}
        assert count == max(each.values(), default=0)
        assert not hits or len({g for q, g in hits if start <= q < start + 9}) == count


def test_repeated_item_rows(spark):
    """More copies of one item than a shard may have rows."""
    items = spark.createDataFrame(ITEMS + [ITEMS[1]] * 50, "item_id long, text string")
    docs = spark.createDataFrame([(1, "no leak"), (3, ITEMS[1][1]), (5, ITEMS[4][1])], "doc_id long, text string")
    got = sorted((r.doc_id, r.item_id) for r in find_contamination(docs, items, match=Match(shard_items=4)).collect())
    assert got == [(3, 2), (5, 5)]


def test_retrieval_is_exact():
    """Block-max pruning retrieves what scoring every piece for every query retrieves."""
    rng = random.Random(6)
    words = [f"t{k}" for k in range(60)]
    items = [(k, " ".join(rng.choices(words, k=rng.randint(5, 30))) + ".") for k in range(40)]
    index = ItemIndex(items, Match(half=16, least_share=0.4))
    known = Words(index.number)
    flat = [(k, {t: v for b in index.postings for t, p in b.items() for kk, v in p if kk == k}) for k in range(len(index.item))]
    for _ in range(50):
        terms = known.terms(" ".join(rng.choices([*words, "zz", "qq", "t1-t2", "--"], k=rng.randint(1, 120))))
        want: dict[int, float] = {}
        for h in range(-(-len(terms) // 16)):
            query = set(terms[h * 16 : (h + 2) * 16].tolist()) - {-1}
            for k, weights in flat:
                s = sum(v for t, v in weights.items() if t in query)
                if s >= 0.4 * index.self_score[k] and s > 0:
                    want[index.item[k]] = max(want.get(index.item[k], 0), s)
        got = dict(index.candidates(terms))
        assert got.keys() == want.keys() and all(got[j] == pytest.approx(want[j]) for j in got)


def test_sample_bound(spark):
    _, docs, labels = labelled(spark, 100)
    model = fit_quality(docs, labels, train_rows=20)
    assert len(model.keys) > 0
