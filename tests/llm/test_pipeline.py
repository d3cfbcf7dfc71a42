import hashlib
import random

import pytest
from tokenizers import Tokenizer

import corpus_pipeline as P
from tests.llm.test_jaccard import brute
from xorvault.llm.compression_rules import Bands, Judge, base_counts
from xorvault.llm.pair_index_bpe import default_vocabulary
from xorvault.llm import secret_guess as S
from xorvault.llm.secret_guess import base_spans, redacted


def brute_run(docs, items):
    judge = Judge(Bands())
    keep = []
    for i, t in docs:
        n, _, _, _, rep = base_counts(t or "")
        if n >= 50 and 100 * rep <= 50 * n and not judge.verdict(t or "")[2]:
            keep.append((i, t))
    classes = brute(keep)
    kept, seen = [], set()
    for k, (i, t) in enumerate(keep):
        if classes[k][0] == i and (i, t) not in seen:
            seen.add((i, t))
            kept.append((i, t))
    squeeze = lambda s: " ".join(s.split())
    kept = [(i, t) for i, t in kept if not any(squeeze(x) in squeeze(t) for x in items)]
    masked = [(i, redacted(t, base_spans(t) + S.loaded(S.default_vocabulary()).spans(t, 9.0))) for i, t in kept]
    library = Tokenizer.from_file(default_vocabulary())
    out = []
    for i, t in masked:
        ids = library.encode(t, add_special_tokens=False).ids
        out.append((i, len(ids), hashlib.sha256(b"".join(k.to_bytes(4, "little") for k in ids)).hexdigest(), hashlib.sha256(library.decode(ids, skip_special_tokens=False).encode()).hexdigest()))
    return sorted(out)


def test_as_brute_force(spark, sf_dir):
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()]
    items = [r.text for r in spark.read.parquet(f"{sf_dir}/benchmark.parquet").collect()]
    got = sorted(tuple(r) for r in P.run(spark, sf_dir).collect())
    assert got == brute_run(docs, items)
    assert 0 < len(got) < len(docs)


def test_stages(spark, sf_dir):
    assert [n for n, _ in P.STAGES] == ["quality_rules", "near_duplicates", "decontamination", "secret_scans", "bpe"]
    rng = random.Random(7)
    prose = lambda: " ".join("".join(rng.choices("etaoinshrdlu", k=rng.randint(3, 9))) for _ in range(70))
    good, other = prose(), prose()
    rows = [(1, good, "en", None, 400), (1, good, "en", None, 400), (2, good + " more", "en", "s", 405), (None, None, None, None, None), (3, "", "en", "s", 0), (4, other + " password=531ccd051a92ebcb68", "en", "s", 9)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").selectExpr("*", "1 AS _kept", "'x' AS _items", "2 AS _masked")
    for name, stage in P.STAGES[:-1]:
        out = stage(spark, docs, sf_dir)
        assert out.columns == docs.columns, name
        assert stage(spark, docs.limit(0), sf_dir).count() == 0
    first = P.quality_stage(spark, docs, sf_dir)
    assert sorted(r.doc_id for r in first.collect()) == [1, 1, 2, 4]
    second = P.near_duplicate_stage(spark, first, sf_dir)
    assert sorted(r.doc_id for r in second.collect()) == [1, 4]
    fourth = {r.doc_id: r for r in P.secret_stage(spark, second, sf_dir).collect()}
    assert fourth[4].text == other + " <secret>" and fourth[4].n_chars == len(fourth[4].text) and fourth[1].n_chars == 400
    assert P.bpe_stage(spark, second, sf_dir).count() == 2


def test_near_duplicates_of_repeated_and_null_ids(spark, sf_dir):
    rng = random.Random(9)
    prose = lambda: " ".join("".join(rng.choices("etaoinshrdlu", k=rng.randint(3, 9))) for _ in range(70))
    a, b, c, d, e = (prose() for _ in range(5))
    rows = [(1, a), (2, b), (2, a), (2, b + " more"), (3, e), (None, c), (None, c), (None, c + " more"), (None, d), (None, e + " more"), (4, ""), (4, ""), (4, d + " more"), (5, None)]
    got = [tuple(r) for r in P.near_duplicate_stage(spark, spark.createDataFrame(rows, "doc_id long, text string"), sf_dir).collect()]
    name = {a: "a", b: "b", b + " more": "b", c: "c", c + " more": "c", d + " more": "d", e: "e", "": "", None: None}
    assert sorted((i or 0, str(name[t])) for i, t in got) == [(0, "c"), (1, "a"), (2, "b"), (3, "e"), (4, ""), (4, "d"), (5, "None")]


@pytest.mark.parametrize("stage", range(5))
def test_stages_on_empty_tables(spark, sf_dir, stage):
    docs = spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")
    assert P.STAGES[stage][1](spark, docs, sf_dir).count() == 0
