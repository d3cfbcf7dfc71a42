"""The pipeline, restoring, fallbacks, families and plans on the zoo."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from tests.oracle import differences
from xorvault import metrics
from xorvault.operators import align, bitdist, dedup, family, graph
from xorvault.plans import hub
from xorvault.sources import archive, zoo
from xorvault.workloads import ORACLES, QUERIES, storage


def rows(df):
    return [tuple(r) for r in df.collect()]


def test_published_projections():
    assert round(metrics.metadata_mib(520_551_953)) == 31_772
    assert metrics.vms(metrics.projected_gb(520_551_953)) == 33
    assert abs(metrics.projected_gb(520_551_953) - 12_505) < 2
    assert round(1 - 41.8 / 43.19, 3) == 0.032 and round(metrics.relative(14.8, 3.2), 1) == 4.6
    assert 8.5e6 * metrics.PRICE_GB_MONTH * 12 > 2.2e6
    assert sum((968, 151, 139, 114, 1431, 47, 135, 63)) == 3048


def test_restore_is_exact(spark, sf_dir):
    t, _ = storage.plain_repos(spark, sf_dir)
    got = hub.verify(hub.restore(storage.built(spark, sf_dir)), t).collect()
    assert len(got) == t.select("repo_id").distinct().count() and all(r.ok for r in got)


@pytest.mark.parametrize("config", [hub.Config(plane_split=True), hub.Config(transform="zigzag"), hub.Config(choose_smaller=False, alignment="normalized_name", standalone=("zstd",)), hub.Config(codec="lz4", tau=4.0)])
def test_variants_restore(spark, sf_dir, config):
    t = zoo.tensors(spark, sf_dir).where("family = 1 AND variant IN ('v0', 'v1', 'v2', 'v5', 'v6', 'v13')")
    r = zoo.repos(spark, sf_dir).join(t.select("repo_id").distinct(), "repo_id", "left_semi")
    store = hub.reduce_hub(t, r, config=config)
    assert all(x.ok for x in hub.verify(hub.restore(store), t).collect())


def test_blocks_take_the_place_of_tensors(spark, sf_dir):
    from xorvault.operators import blocks

    t = zoo.tensors(spark, sf_dir).where("family = 2 AND variant IN ('v0', 'v1', 'v3', 'v13')")
    b = blocks.as_blocks(t, block_bytes=256)
    assert b.count() > t.count() and b.agg(F.sum("n_bytes")).first()[0] == t.agg(F.sum("n_bytes")).first()[0]
    r = zoo.repos(spark, sf_dir).join(t.select("repo_id").distinct(), "repo_id", "left_semi")
    store = hub.reduce_hub(b, r)
    assert all(x.ok for x in hub.verify(hub.restore(store), b).collect())
    d = lambda x: {(q.a, q.b): q.distance for q in bitdist.bit_distance(graph.aligned_blocks(graph.pairs_of(graph.signature(x)), x)).collect()}
    assert d(b) == d(t)
    rows_ = blocks.as_blocks(t.withColumn("path", F.concat_ws("/", "path", F.col("ordinal").cast("string"))), block_bytes=1 << 20)
    one = blocks.tensor_hashes(rows_.select("repo_id", "path", F.col("ordinal").alias("block_no"), F.col("tensor_hash").alias("block_hash"), "n_bytes"), keys=("repo_id", "path"))
    assert {x.tensor_hash for x in one.collect()} == {x.tensor_hash for x in t.select("tensor_hash").collect()}
    with pytest.raises(ValueError):
        blocks.as_blocks(t, block_bytes=12)


def test_bytes_are_fetched_late(spark, sf_dir):
    """Deduplication, lineage and pairing see no payload column."""
    store = hub.reduce_hub(zoo.tensors(spark, sf_dir), zoo.repos(spark, sf_dir))
    for part in (store.links, store.manifests):
        assert not any("payload" in line for line in explained(part).split("\n") if line.startswith("ReadSchema"))


def test_later_uploads(spark, sf_dir, tmp_path):
    """Two batches of uploads pool the same tensors as one, and everything restores."""
    t = zoo.tensors(spark, sf_dir).where("family = 3 AND variant NOT IN ('v10', 'v11')")
    r = zoo.repos(spark, sf_dir).join(t.select("repo_id").distinct(), "repo_id", "left_semi")
    early, late = t.where("variant IN ('v0', 'v2')"), t.where("variant NOT IN ('v0', 'v2')")
    first = hub.reduce_hub(early, r.join(early.select("repo_id").distinct(), "repo_id", "left_semi")).written(str(tmp_path / "a"))
    both = hub.compact(hub.reduce_hub(late, r, after=first, bases=early), str(tmp_path / "b"))
    once = hub.reduce_hub(t, r)
    assert sorted(rows(both.pool.select("pool_key"))) == sorted(rows(once.pool.select("pool_key")))
    got = hub.verify(hub.restore(both), t).collect()
    assert len(got) == r.count() and all(x.ok for x in got)
    assert {x.repo_id for x in both.links.collect()} == {"m3_v1"}


def test_base_uploaded_last(spark, sf_dir):
    """Tuned models may come before their base: what they share with it is never a delta against itself."""
    t = zoo.tensors(spark, sf_dir).where("family = 4 AND variant IN ('v0', 'v2', 'v12', 'v12c')")
    r = zoo.repos(spark, sf_dir).join(t.select("repo_id").distinct(), "repo_id", "left_semi").withColumn("seq", -F.col("seq"))
    store = hub.reduce_hub(t, r)
    assert all(x.ok for x in hub.verify(hub.restore(store), t).collect())
    assert store.pool.where("base_hash = tensor_hash").count() == 0 and hub.chain(store.pool).agg(F.max("depth")).first()[0] == 1
    with_late_base = hub.reduce_hub(t.where("variant = 'v0'"), r, after=hub.reduce_hub(t.where("variant <> 'v0'"), r.where("variant <> 'v0'")))
    assert all(x.ok for x in hub.verify(hub.restore(with_late_base), t).collect())


def test_levels_nest(spark, sf_dir):
    d = {r.level: r.drr for r in QUERIES["dedup_levels_zoo"](spark, sf_dir).collect()}
    assert d["file"] <= d["layer"] <= d["tensor"]


def test_order_of_methods(spark, sf_dir):
    d = {r.method: r.drr for r in QUERIES["order_ablation"](spark, sf_dir).collect()}
    assert d["engine"] == max(d.values())
    assert d["engine"] >= d["xor then chunks"] > max(d["grouping then chunks"], d["zstd then chunks"]) > d["chunks"] > d["files"]


def test_pool_accounts(spark, sf_dir):
    t = zoo.tensors(spark, sf_dir).drop("payload")
    found = dedup.dedup_tensors(t)
    assert found.pool.agg(F.sum("refcount")).first()[0] == t.count()
    assert found.refs.where("NOT is_dup").agg(F.sum("n_bytes")).first()[0] == found.pool.agg(F.sum("n_bytes")).first()[0]
    assert sorted(rows(dedup.dedup_tensors(t.repartition(7)).pool)) == sorted(rows(found.pool))


def test_incremental_is_batch(spark, sf_dir):
    files = dedup.files_of(zoo.tensors(spark, sf_dir)).withColumnRenamed("unit_hash", "file_hash")
    old, new = files.where("repo_id < 'm3'"), files.where("repo_id >= 'm3'")
    unseen, links = dedup.dedup_against(new, old.select("file_hash").distinct())
    once = {r.file_hash for r in old.collect()} | {r.file_hash for r in unseen.collect()}
    assert once == {r.file_hash for r in files.collect()} and unseen.count() + links.count() == new.count()


def test_garbage(spark, sf_dir):
    store = storage.built(spark, sf_dir)
    left, fate = hub.collect_garbage(store, ["m0_v0", "m0_v1"])
    assert {r.fate for r in fate.collect()} >= {"kept"}
    keep = [r.repo_id for r in left.manifests.select("repo_id").distinct().collect()]
    t = zoo.tensors(spark, sf_dir).where(F.col("repo_id").isin(keep) & (F.col("variant") != "v10") & (F.col("variant") != "v11"))
    assert all(r.ok for r in hub.verify(hub.restore(left, keep), t).collect())


def test_surrogate_is_exact(spark, sf_dir):
    plan = storage._surrogate(spark, sf_dir)
    assert plan.where("NOT ok").count() == 0
    best = hub.choose_smaller(plan).first()
    assert best.n_stored == plan.groupBy("mode").agg(F.sum("n_stored").alias("s")).agg(F.min("s")).first()[0]


def test_sampled_distance_holds(spark, sf_dir):
    p = storage.blocks(spark, sf_dir, storage.family_pairs(spark, sf_dir))
    full = {(r.a, r.b): r.distance for r in bitdist.bit_distance(p).collect()}
    for r in bitdist.bit_distance_sampled(p, rate=0.6, delta=0.01).collect():
        assert abs(r.distance - full[r.a, r.b]) <= r.half_width
    assert {(r.a, r.b): r.distance for r in bitdist.bit_distance_sampled(p, rate=1.0).collect()} == full


def test_distance_grows_with_sigma(spark, sf_dir):
    changed = storage.blocks(spark, sf_dir, storage.family_pairs(spark, sf_dir)).where("payload_a <> payload_b")  # without frozen tensors
    d = {r.b: r.distance for r in bitdist.bit_distance(changed).collect()}
    for f in range(10):
        assert d[f"m{f}_v2"] < d[f"m{f}_v3"] < d[f"m{f}_v4"]


def test_monte_carlo(spark):
    got = {(r.sigma_w, r.sigma_d): r.expected for r in family.expected_grid(spark, [0.01, 0.05], [0.0, 0.001, 0.01], n=20_000).collect()}
    for w in (0.01, 0.05):
        assert got[w, 0.0] == 0 < got[w, 0.001] < got[w, 0.01]
    assert got[0.05, 0.001] < got[0.01, 0.001]
    for g in ("box_muller", "randn"):
        other = family.expected_distance(spark, 0.01, 0.001, n=20_000, generator=g).first().expected
        assert abs(other - got[0.01, 0.001]) < 0.05


def test_sweep_and_pick(spark):
    df = spark.createDataFrame([(1.0, True), (2.0, True), (5.0, True), (4.5, False), (6.0, False)], "distance double, actual boolean")
    s = family.sweep(df, [0.5, 3.0, 4.75, 9.0])
    got = {r.tau: (r.tp, r.fp, r.tn, r.fn) for r in s.collect()}
    assert got == {0.5: (0, 0, 2, 3), 3.0: (2, 0, 2, 1), 4.75: (2, 1, 1, 1), 9.0: (3, 2, 0, 0)}
    assert s.where("tau = 0.5").first().precision is None
    assert family.pick(s) == 3.0 and family.pick(s, "guarded", 4.5) == 3.0


def test_alignment_modes(spark, sf_dir):
    t = zoo.tensors(spark, sf_dir).where("family = 0")
    tuned = t.where("variant = 'v6'").withColumn("base_repo", F.lit("m0_v0"))
    base = t.where("variant = 'v0'")
    met = {m: align.align(tuned, base, by=m).where("base_hash IS NOT NULL").count() for m in ("order", "name", "normalized_name")}
    assert met["name"] == 0 < met["normalized_name"]


def test_classify_and_graph(spark):
    pairs = spark.createDataFrame([("s", "s", 3.9), ("s", "s", 4.0), ("s", "t", 1.0), ("s", "s", None)], "signature_a string, signature_b string, distance double")
    assert [(r.rule, r.predicted) for r in family.classify_pairs(pairs).collect()] == [("distance", True), ("distance", False), ("structure", False), ("distance", False)]
    edges = spark.createDataFrame([("b", "c"), ("c", "d"), ("x", "y")], "a string, b string")
    nodes = spark.createDataFrame([(n,) for n in "abcdxyz"], "node string")
    got = {r.node: r.component for r in graph.components(nodes, edges).collect()}
    assert got == {"a": "a", "b": "b", "c": "b", "d": "b", "x": "x", "y": "x", "z": "z"}


def test_every_base_of_like_structure_is_compared(spark):
    """Seven bases of one structure; the models without a hint descend from the last by name."""
    rng = np.random.default_rng(6)
    base = {f"b{k}": rng.integers(0, 1 << 16, 64).astype("<u2") for k in range(7)}
    card = {f"t{k}": f"---\nbase_model: b{k}\n---\n" for k in range(7)}
    words_ = base | {f"t{k}": base[f"b{k}"] ^ 1 for k in range(7)} | {"x5": base["b5"] ^ 2, "x6": base["b6"] ^ 2}
    t = spark.createDataFrame([(n, 0, "BF16", [1, 64], bytearray(w.tobytes())) for n, w in words_.items()], "repo_id string, ordinal int, dtype string, shape array<bigint>, payload binary")
    r = spark.createDataFrame([(n, card.get(n), "{not json") for n in words_], "repo_id string, card string, config string")
    got = {x.repo_id: (x.base, x.source) for x in hub.assign_bases(t, t.select("repo_id"), r, hub.Config(tau=4.0)).collect()}
    assert got["x5"] == ("b5", "distance") and got["x6"] == ("b6", "distance")


def test_sweeps_have_pairs_across_families(spark, sf_dir):
    swept = QUERIES["threshold_sweep_zoo"](spark, sf_dir).collect()
    assert all(r.fp + r.tn > 0 for r in swept) and len({r.tp + r.fp + r.tn + r.fn for r in swept}) == 1
    assert all(r.fp + r.tn > 0 for r in QUERIES["threshold_pick"](spark, sf_dir).collect())
    pairs = QUERIES["bitdist_pairs"](spark, sf_dir)
    assert pairs.count() == swept[0].tp + swept[0].fp + swept[0].tn + swept[0].fn
    families = zoo.tensors(spark, sf_dir).select("family").distinct().count()
    assert pairs.select(F.split("a", "_")[0]).distinct().count() == families
    assert QUERIES["classify_pairs"](spark, sf_dir).where("NOT actual AND rule = 'distance'").count() > 0


def test_monte_carlo_draws(spark, sf_dir):
    n = spark.read.parquet(f"{sf_dir}/embeddings.parquet").agg(F.sum(F.size("embedding"))).first()[0]  # every weight is drawn
    made = {r.generator: r for r in QUERIES["mc_generators"](spark, sf_dir).collect()}
    assert {r.n for r in made.values()} == {n} and max(r.expected for r in made.values()) - min(r.expected for r in made.values()) < 0.05
    grid = {(r.sigma_w, r.sigma_d): r for r in QUERIES["mc_expected_grid"](spark, sf_dir).collect()}
    assert len(grid) == 42 and {r.n for r in grid.values()} == {n}
    assert grid[0.02, 0.002].expected == QUERIES["mc_point"](spark, sf_dir).first().expected


@pytest.mark.parametrize("name", ["mc_expected_grid", "mc_point", "mc_generators"])
def test_monte_carlo_reads_its_weights(spark, tmp_path, name):
    """The draws follow the table, odd values left out, and agree with the SQL twin."""
    odd = "array(CAST(0.5 AS FLOAT), CAST(-0.25 AS FLOAT), CAST('NaN' AS FLOAT), CAST('Infinity' AS FLOAT), CAST(NULL AS FLOAT), CAST(0 AS FLOAT))"
    spark.range(40).selectExpr("id AS vec_id", f"CASE WHEN id < 30 THEN {odd} END AS embedding", "CAST(id % 3 AS INT) AS label").coalesce(1).write.parquet(f"{tmp_path}/embeddings.parquet")
    assert {r.n for r in QUERIES[name](spark, str(tmp_path)).collect()} == {90}
    if name in ORACLES:
        con = duckdb.connect()
        con.execute(f"CREATE VIEW embeddings AS SELECT * FROM '{tmp_path}/embeddings.parquet/*.parquet'")
        assert differences(QUERIES[name](spark, str(tmp_path)), con, ORACLES[name]) == ""


def test_index_of_the_table_that_is_there(spark, tmp_path):
    """Two texts and three lines of 9 bytes; no row for a null."""
    spark.createDataFrame([("a\nb",), ("a\nb",), ("b\nc",), (None,)], "text string").coalesce(1).write.parquet(f"{tmp_path}/documents.parquet")
    df = QUERIES["metadata_published"](spark, str(tmp_path))
    counts = {"file": 2, "line": 3}
    assert {r.level: r.projected_gb for r in df.collect()} == {k: round(metrics.projected_gb(n, sample_tb=9e-12), 3) for k, n in counts.items()}
    assert {r.level: r.metadata_mib for r in df.collect()} == {k: round(n * 64 / 2**20, 6) for k, n in counts.items()}
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/documents.parquet/*.parquet'")
    assert differences(df, con, ORACLES["metadata_published"]) == ""


def test_capabilities_are_measured(spark, sf_dir, monkeypatch):
    """A technique that stores its input as it is loses its flags."""
    monkeypatch.setitem(storage.TECHNIQUES, "zstd", (None, storage._kept))
    monkeypatch.setitem(storage.TECHNIQUES, "xor delta", (storage._whole, storage._kept))
    got = {r.technique: (r.dedup, r.compression, r.cross_model, r.lossless) for r in QUERIES["capabilities"](spark, sf_dir).collect()}
    assert got["zstd"] == (False, False, False, True) and got["xor delta"] == (True, False, False, True) and got["engine"] == (True,) * 4


def test_items_in_parts(spark, sf_dir, monkeypatch):
    from xorvault.workloads import models

    whole = sorted(rows(QUERIES["lineage_benchmark"](spark, sf_dir)))
    n = spark.read.parquet(f"{sf_dir}/benchmark.parquet").count()
    monkeypatch.setattr(models, "ITEMS_A_SCAN", n // 2)
    assert sorted(rows(QUERIES["lineage_benchmark"](spark, sf_dir))) == whole != []


def test_undecided_pairs_get_a_full_pass(spark, sf_dir):
    from xorvault.workloads import models

    full = {(r.a, r.b): r.distance for r in bitdist.bit_distance(models.blocks(spark, sf_dir, models.family_pairs(spark, sf_dir))).collect()}
    got = QUERIES["bitdist_sampled"](spark, sf_dir).collect()
    assert sorted((r.a, r.b) for r in got) == sorted(full) and all(r.decided for r in got)
    assert all(abs(r.distance - full[r.a, r.b]) <= r.half_width for r in got) and any(r.half_width == 0 for r in got)


def explained(df):
    return df.sparkSession._jvm.org.apache.spark.sql.api.python.PythonSQLUtils.explainString(df._jdf.queryExecution(), "formatted")


def test_plans(spark, sf_dir):
    plan = explained(QUERIES["scan_prune_lineitem"](spark, sf_dir))
    assert "GreaterThan(l_discount" in plan and "l_extendedprice" not in plan.split("ReadSchema")[1].split("\n")[0]
    for name in ("bitdist_pairs", "nearest_base", "dedup_levels_zoo", "join_theta_tau"):
        assert "CartesianProduct" not in QUERIES[name](spark, sf_dir)._jdf.queryExecution().executedPlan().toString()


# --- Archives


def sample():
    rng = np.random.default_rng(3)
    return [("a.weight", "BF16", [2, 3], rng.bytes(12)), ("b", "F32", [], rng.bytes(4)), ("empty", "BF16", [0], b"")]


def test_archive_roundtrip():
    data = archive.write_archive(sample(), {"k": "v"})
    h = archive.parse(data)
    assert h.metadata == {"k": "v"} and [t["name"] for t in h.tensors] == ["a.weight", "b", "empty"] or {t["name"] for t in h.tensors} == {"a.weight", "b", "empty"}
    body = data[h.data_at :] + b"odd tail"
    units = archive.with_filler(h.tensors, len(body))
    assert b"".join(body[u["begin"] : u["end"]] for u in units) == body
    with pytest.raises(ValueError):
        archive.read_header(data[:20])
    q = archive.write_quantized([("q", [4], b"abcd"), ("r", [1, 2], b"xy")], {"bits": 8})
    assert [t["name"] for t in archive.parse(q).tensors] == ["q", "r"] and archive.parse(q).metadata == {"bits": 8}


def test_extract_and_data_source(spark, tmp_path):
    data = archive.write_archive(sample())
    files = spark.createDataFrame([("r", "m.tensors", bytearray(data)), ("r", "q.qtensors", bytearray(archive.write_quantized([("q", [4], b"abcd")], {})))], "repo_id string, path string, content binary")
    t = archive.extract_tensors(files)
    assert {(r.path, r.name): bytes(r.payload) for r in t.collect()}[("q.qtensors", "q")] == b"abcd"
    archive.register(spark)
    rows_ = [("x/m.tensors", k, n, d, s, p) for k, (n, d, s, p) in enumerate(sample())]
    spark.createDataFrame(rows_, "file string, ordinal int, name string, dtype string, shape array<bigint>, payload binary").coalesce(1).write.format("tensor_archive").mode("append").save(str(tmp_path))
    back = spark.read.format("tensor_archive").load(str(tmp_path))
    assert {(r.name, bytes(r.payload)) for r in back.collect()} == {(n, p) for n, _, _, p in sample()}
    assert [r.name for r in back.where("dtype = 'F32'").collect()] == ["b"]
    assert archive.read_headers(spark, str(tmp_path)).count() == 3


def test_restored_files(spark, sf_dir, tmp_path):
    t = zoo.tensors(spark, sf_dir).where("repo_id = 'm0_v3'")
    parts = [(r.name, r.dtype, list(r.shape), bytes(r.payload)) for r in t.orderBy("ordinal").collect()]
    data = archive.write_archive(parts)
    headers = spark.createDataFrame([("m0_v3", "model.tensors", bytearray(archive.read_header(data).raw))], "repo_id string, path string, header binary")
    hub.write_files(hub.restore(storage.built(spark, sf_dir), ["m0_v3"]), headers, str(tmp_path)).collect()
    assert (tmp_path / "m0_v3" / "model.tensors").read_bytes() == data


def test_folders_of_repositories(spark, tmp_path):
    for repo, base in (("r1", None), ("r2", "r1")):
        (tmp_path / repo).mkdir()
        (tmp_path / repo / "m.tensors").write_bytes(archive.write_archive(sample()))
        (tmp_path / repo / "README.md").write_text(f"---\nbase_model: {base}\n---\n" if base else "hello")
    (tmp_path / "r1" / "config.json").write_text('{"family": "f"}')
    files = archive.read_files(spark, str(tmp_path), glob="*.tensors")
    assert archive.extract_tensors(files).count() == 2 * len(sample()) - 0
    assert files.groupBy(F.sha2("content", 256)).count().first()["count"] == 2
    told = {r.repo_id: (r.status, r.base) for r in family.from_metadata(archive.read_cards(spark, str(tmp_path))).collect()}
    assert told == {"r1": ("ambiguous", None), "r2": ("exact", "r1")}


def test_children_of_one_base_are_spread(spark):
    """5,000 of 6,000 children have one base, and don't land in one task."""
    own, base = ["repo_id", "path", "ordinal"], ["base_repo", "base_path", "base_ordinal"]
    rows = spark.range(6_000).select(F.concat(F.lit("m"), "id").alias("repo_id"), F.lit("p").alias("path"), F.lit(0).alias("ordinal"), F.when(F.col("id") < 5000, "hot").otherwise(F.concat(F.lit("b"), F.col("id") % 200)).alias("base_repo"))
    children = rows.withColumns({"base_path": F.lit("p"), "base_ordinal": F.lit(0)})
    payloads = rows.select(*own, F.col("repo_id").cast("binary").alias("payload"))
    bases = children.select(*base).distinct().withColumn("payload_b", F.col("base_repo").cast("binary"))
    old = {k: spark.conf.get(k) for k in ("spark.sql.shuffle.partitions", "spark.sql.adaptive.enabled", "spark.sql.autoBroadcastJoinThreshold")}
    try:
        spark.conf.set("spark.sql.shuffle.partitions", "16")
        spark.conf.set("spark.sql.adaptive.enabled", "false")
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
        made = hub.with_bases(children, payloads, bases, own=own, base=base)
        sizes = sorted(r["n"] for r in made.groupBy(F.spark_partition_id().alias("p")).agg(F.count("*").alias("n")).collect())
        got = made.select(F.count("*"), F.bool_and(F.col("payload_b").cast("string") == F.col("base_repo"))).first()
    finally:
        for k, v in old.items():
            spark.conf.set(k, v)
    assert tuple(got) == (6000, True)
    assert sizes[-1] <= 3 * sizes[len(sizes) // 2] and len(sizes) == 16


def test_tensors_without_a_base_skip_the_join(spark, sf_dir):
    """Their payloads go around the joins on base tensors: no join has a null key to gather them by."""
    pool = storage.built(spark, sf_dir).pool
    plan = explained(hub.decoded_pool(pool))
    assert "Union" in plan
    filters = [line for line in plan.split("\n") if line.startswith("PushedFilters") and "base_hash" in line]
    assert any("IsNull(base_hash)" in f for f in filters) and any("IsNotNull(base_hash)" in f for f in filters)
