"""Workloads on model bits and families: deltas, distances, breakdowns, graph, lineage, matching, Monte Carlo, thresholds."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from xorvault.functions.words import differing, double_bits, float_bits
from xorvault.operators import align, bitdist, family, graph, timeseries
from xorvault.sources import zoo
from xorvault.workloads import zoo_sql as Z
from xorvault.workloads.registry import query, table

TUNED = ("v2", "v3", "v4")


def family_pairs(spark, sf_dir, others: tuple[str, ...] = TUNED, base: str = "v0") -> DataFrame:
    """(a, b) of each family's base and its variants."""
    m = zoo.tensors(spark, sf_dir).select("repo_id", "family", "variant").distinct()
    a = m.where(F.col("variant") == base).select("family", F.col("repo_id").alias("a"))
    return a.join(m.where(F.col("variant").isin(*others)).select("family", F.col("repo_id").alias("b")), "family").select("a", "b")


def cross_pairs(spark, sf_dir) -> DataFrame:
    """Bases of neighbouring families."""
    m = zoo.tensors(spark, sf_dir).where("variant = 'v0'").select("repo_id", "family").distinct()
    return m.alias("x").join(m.alias("y"), F.expr("y.family = x.family + 1")).select(F.col("x.repo_id").alias("a"), F.col("y.repo_id").alias("b"))


def blocks(spark, sf_dir, pairs: DataFrame) -> DataFrame:
    return graph.aligned_blocks(pairs, zoo.tensors(spark, sf_dir))


CROSS = "pe AS (SELECT p.repo_id AS a, q.repo_id AS b, p.x, q.x AS y FROM (SELECT family, repo_id, ordinal, idx, bits AS x FROM el WHERE variant = 'v0') p JOIN (SELECT family, repo_id, ordinal, idx, bits AS x, max(idx) OVER (PARTITION BY family, ordinal) AS m FROM el WHERE variant = 'v0') q ON q.family = p.family + 1 AND p.ordinal = q.ordinal AND p.idx = q.idx JOIN (SELECT family, ordinal, max(idx) AS m FROM el WHERE variant = 'v0' GROUP BY 1, 2) pm ON pm.family = p.family AND pm.ordinal = p.ordinal AND pm.m = q.m)"


def _values(spark, sf_dir, where: str) -> DataFrame:
    return zoo.elements(spark, sf_dir).where(where).where("dtype = 'BF16'").select("repo_id", "family", "variant", "ordinal", "idx", bitdist.value_of_bf16().alias("value"))


def _within_deltas(spark, sf_dir) -> DataFrame:
    v = _values(spark, sf_dir, "variant IN ('v0', 'v2', 'v3', 'v4')")
    b = v.where("variant = 'v0'").select("family", "ordinal", "idx", F.col("repo_id").alias("b"), F.col("value").alias("w"))
    return v.where("variant <> 'v0'").join(b, ["family", "ordinal", "idx"]).select(F.col("repo_id").alias("a"), "b", (F.col("value") - F.col("w")).alias("dw"))


DW = f"({Z.VALUE.format(b='y')}) - ({Z.VALUE.format(b='x')})"


@query("delta_hist_within", lambda: f"WITH {Z.elements(('v0', *TUNED))}, {Z.pairs()} SELECT b AS a, a AS b, CAST(floor(({DW}) / 0.001) AS BIGINT) AS bin, count(*) AS cnt FROM pe WHERE dtype = 'BF16' GROUP BY ALL")
def delta_hist_within(spark, sf_dir):
    """Histogram of element deltas of tuned models against their base."""
    return bitdist.delta_profile(_within_deltas(spark, sf_dir))


def _cross_deltas(spark, sf_dir) -> DataFrame:
    v = _values(spark, sf_dir, "variant = 'v0'")
    n = v.groupBy("repo_id", "ordinal").agg(F.count("*").alias("n"))
    v = v.join(n, ["repo_id", "ordinal"])
    y = v.select((F.col("family") - 1).alias("family"), "ordinal", "idx", "n", F.col("repo_id").alias("b"), F.col("value").alias("w"))
    return v.join(y, ["family", "ordinal", "idx", "n"]).select(F.col("repo_id").alias("a"), "b", (F.col("value") - F.col("w")).alias("dw"))


@query("delta_hist_cross", lambda: f"WITH {Z.elements(('v0',))}, {CROSS} SELECT a, b, CAST(floor((({Z.VALUE.format(b='x')}) - ({Z.VALUE.format(b='y')})) / 0.001) AS BIGINT) AS bin, count(*) AS cnt FROM pe GROUP BY ALL")
def delta_hist_cross(spark, sf_dir):
    """The same against the next family's base, over tensors of equal shape."""
    return bitdist.delta_profile(_cross_deltas(spark, sf_dir))


@query("delta_moments", lambda: f"WITH {Z.elements(('v0', *TUNED))}, {Z.pairs()} SELECT b AS a, a AS b, count(*) AS n, round(avg({DW}), 7) AS mean, round(stddev_pop({DW}), 7) AS sd, max(abs({DW})) AS max_abs FROM pe WHERE dtype = 'BF16' GROUP BY ALL")
def delta_moments(spark, sf_dir):
    m = bitdist.delta_moments(_within_deltas(spark, sf_dir))
    return m.select("a", "b", "n", F.round("mean", 7).alias("mean"), F.round("sd", 7).alias("sd"), "max_abs")


@query("delta_shape")
def delta_shape(spark, sf_dir):
    """Skewness, kurtosis and median of deltas within families and across them."""
    parts = [bitdist.delta_moments(d).select(F.lit(k).alias("kind"), "a", "b", "skew", "kurt", "median") for k, d in (("within", _within_deltas(spark, sf_dir)), ("cross", _cross_deltas(spark, sf_dir)))]
    return parts[0].unionAll(parts[1])


DIST = "count(*) AS n, CAST(sum(bit_count(CAST(xor(x, y) AS BIGINT))) AS BIGINT) AS bits, round(CAST(sum(bit_count(CAST(xor(x, y) AS BIGINT))) AS DOUBLE) / count(*), 6) AS distance"
NOT_BOTH_ZERO = "NOT ((x & 32767) = 0 AND (y & 32767) = 0)"
PAIRS = "pe AS (SELECT p.repo_id AS a, q.repo_id AS b, p.bits AS x, q.bits AS y FROM el p JOIN el q ON p.family = q.family AND p.ordinal = q.ordinal AND p.idx = q.idx AND p.repo_id < q.repo_id)"


def compared(spark, sf_dir) -> DataFrame:
    """Tensors of the comparable variants of every family, with `true_family`: v12 is a base of its own, and v12c its model."""
    other = F.when(F.col("variant").isin("v12", "v12c"), "_v12").otherwise("")
    return zoo.tensors(spark, sf_dir).where(F.col("variant").isin(*zoo.COMPARABLE)).withColumn("true_family", F.concat(F.col("family").cast("string"), other))


def _pairwise(spark, sf_dir) -> DataFrame:
    t = compared(spark, sf_dir)
    return bitdist.bit_distance(graph.aligned_blocks(graph.pairs_of(graph.signature(t)), t))


OTHER_BASE = "CASE WHEN variant IN ('v12', 'v12c') THEN '_v12' ELSE '' END"
ALL_PAIRS = f"""{{elements}}, el AS (SELECT *, family || {OTHER_BASE} AS tf FROM el0), sg AS (SELECT family, max(ordinal) AS mo, count(*) AS n FROM el WHERE variant = 'v0' GROUP BY 1),
pe AS (SELECT p.repo_id AS a, q.repo_id AS b, p.tf = q.tf AS same, p.bits AS x, q.bits AS y FROM el p JOIN el q ON p.ordinal = q.ordinal AND p.idx = q.idx AND p.repo_id < q.repo_id JOIN sg s ON s.family = p.family JOIN sg r ON r.family = q.family AND r.n = s.n)"""


def all_pairs(variants: tuple[str, ...] = zoo.COMPARABLE) -> str:
    """pe: aligned elements of all pairs of equal structure, with `same`: are they of one true family?"""
    return ALL_PAIRS.format(elements=Z.elements(variants).replace("el AS", "el0 AS", 1))


@query("bitdist_pairs", lambda: f"WITH {all_pairs()} SELECT a, b, {DIST} FROM pe WHERE {NOT_BOTH_ZERO} GROUP BY 1, 2")
def bitdist_pairs(spark, sf_dir):
    """Bit distances of all pairs of equal structure."""
    return _pairwise(spark, sf_dir)


@query("bitdist_sql_path", lambda: f"WITH {Z.elements(('v0', *TUNED))}, {Z.pairs()} SELECT a, b, {DIST} FROM pe WHERE {NOT_BOTH_ZERO} GROUP BY 1, 2")
def bitdist_sql_path(spark, sf_dir):
    """The element path in Catalyst expressions."""
    return bitdist.bit_distance_sql(zoo.elements(spark, sf_dir).where("dtype = 'BF16'"), family_pairs(spark, sf_dir))


@query("bitdist_zero_policies", lambda: f"""WITH {Z.elements(('v0', 'v7', 'v8'))}, {Z.pairs('v7', ('v8',))}
SELECT a, b, 'drop_both_zero' AS policy, {DIST} FROM pe WHERE {NOT_BOTH_ZERO} GROUP BY 1, 2 UNION ALL SELECT a, b, 'drop_either_zero', {DIST} FROM pe WHERE NOT ((x & 32767) = 0 OR (y & 32767) = 0) GROUP BY 1, 2 UNION ALL SELECT a, b, 'keep', {DIST} FROM pe GROUP BY 1, 2""")
def bitdist_zero_policies(spark, sf_dir):
    """Two models pruned at the same positions, under each zero policy."""
    b = blocks(spark, sf_dir, family_pairs(spark, sf_dir, ("v8",), "v7"))
    made = [bitdist.bit_distance(b, zero_policy=p).select("a", "b", F.lit(p).alias("policy"), "n", "bits", "distance") for p in bitdist.POLICIES]
    return made[0].unionAll(made[1]).unionAll(made[2])


@query("bitdist_sampled")
def bitdist_sampled(spark, sf_dir):
    """Sampled distances with their bound where they decide the threshold, and exact ones of the other pairs."""
    return bitdist.bit_distance_settled(blocks(spark, sf_dir, family_pairs(spark, sf_dir)), rate=0.5)


@query("bitdist_dtypes", """WITH v AS (SELECT vec_id, unnest(range(64)) AS i, unnest(embedding) AS x FROM embeddings), w AS (SELECT vec_id, i, CAST(CAST(CAST(x / 4 AS FLOAT) AS BIT) AS INTEGER) AS b FROM v)
SELECT p.vec_id, count(*) AS n, CAST(sum(bit_count(xor(p.b, q.b))) AS BIGINT) AS bits FROM w p JOIN w q ON q.vec_id = p.vec_id + 1 AND p.i = q.i WHERE NOT ((p.b & 2147483647) = 0 AND (q.b & 2147483647) = 0) GROUP BY 1""")
def bitdist_dtypes(spark, sf_dir):
    """FP32 distances of neighbouring raw vectors."""
    return _vector_distances(spark, sf_dir, 1).select("vec_id", "n", "bits")


def _vector_distances(spark, sf_dir, step: int) -> DataFrame:
    e = table(spark, sf_dir, "embeddings").select("vec_id", "label", F.posexplode("embedding").alias("i", "x"))
    w = e.select("vec_id", "label", "i", float_bits((F.col("x") / 4).cast("float")).alias("b"))
    other = w.select((F.col("vec_id") - step).alias("vec_id"), "i", F.col("b").alias("c"), F.col("label").alias("label_b"))
    zero = lambda c: F.col(c).bitwiseAND(0x7FFFFFFF) == 0
    both = w.join(other, ["vec_id", "i"]).where(~(zero("b") & zero("c")))
    return both.groupBy("vec_id", "label", "label_b").agg(F.count("*").alias("n"), F.sum(differing(F.col("b"), F.col("c"))).cast("bigint").alias("bits"))


@query("bitdist_embeddings_control", """WITH v AS (SELECT vec_id, label, unnest(range(64)) AS i, unnest(embedding) AS x FROM embeddings), w AS (SELECT vec_id, label, i, CAST(CAST(CAST(x / 4 AS FLOAT) AS BIT) AS INTEGER) AS b FROM v),
d AS (SELECT p.label = q.label AS same, count(*) AS n, sum(bit_count(xor(p.b, q.b))) AS bits FROM w p JOIN w q ON q.vec_id = p.vec_id + 7 AND p.i = q.i WHERE NOT ((p.b & 2147483647) = 0 AND (q.b & 2147483647) = 0) GROUP BY 1)
SELECT same AS same_label, CAST(n AS BIGINT) AS n, CAST(bits AS BIGINT) AS bits, round(CAST(bits AS DOUBLE) / n, 6) AS distance FROM d""")
def bitdist_embeddings_control(spark, sf_dir):
    """Negative control: raw vectors of one label are no closer in bits than those of different labels."""
    d = _vector_distances(spark, sf_dir, 7).groupBy((F.col("label") == F.col("label_b")).alias("same_label")).agg(F.sum("n").alias("n"), F.sum("bits").alias("bits"))
    return d.withColumn("distance", F.round(F.col("bits") / F.col("n"), 6))


FIELD = "CASE WHEN k = {s} THEN 'sign' WHEN k >= {e} THEN 'exponent' ELSE 'mantissa' END"


def _breakdown_sql(width: int, exponent: int, by: str, source: str) -> str:
    keys = f"{by}, " if by else ""
    return f"""o AS (SELECT {keys}CAST(k AS INTEGER) AS k, CAST(sum((xor(x, y) >> k) & 1) AS BIGINT) AS ones FROM {source}, (SELECT unnest(range({width})) AS k) GROUP BY ALL)
SELECT {keys}k AS bit_pos, {FIELD.format(s=width - 1, e=width - 1 - exponent)} AS field, ones, round(CAST(ones AS DOUBLE) / sum(ones) OVER ({'PARTITION BY ' + by if by else ''}), 6) AS share FROM o"""


@query("bit_breakdown_within", lambda: f"WITH {Z.elements(('v0', *TUNED))}, {Z.pairs()}, " + _breakdown_sql(16, 8, "a, b", "pe"))
def bit_breakdown_within(spark, sf_dir):
    return bitdist.bit_breakdown(blocks(spark, sf_dir, family_pairs(spark, sf_dir)))


@query("bit_breakdown_cross", lambda: f"WITH {Z.elements(('v0',))}, {CROSS}, " + _breakdown_sql(16, 8, "a, b", "pe"))
def bit_breakdown_cross(spark, sf_dir):
    return bitdist.bit_breakdown(blocks(spark, sf_dir, cross_pairs(spark, sf_dir)))


@query("bit_breakdown_fp64", """WITH pe AS (SELECT CAST(CAST(l_extendedprice AS BIT) AS BIGINT) AS x, CAST(CAST(l_extendedprice * (1 - l_discount) AS BIT) AS BIGINT) AS y FROM lineitem),
o AS (SELECT CAST(k AS INTEGER) AS k, CAST(sum(CAST(substr(CAST(CAST(xor(x, y) AS BIT) AS VARCHAR), CAST(64 - k AS BIGINT), 1) AS INTEGER)) AS BIGINT) AS ones FROM pe, (SELECT unnest(range(64)) AS k) GROUP BY ALL)
SELECT k AS bit_pos, CASE WHEN k = 63 THEN 'sign' WHEN k >= 52 THEN 'exponent' ELSE 'mantissa' END AS field, ones, round(CAST(ones AS DOUBLE) / sum(ones) OVER (), 6) AS share FROM o""")
def bit_breakdown_fp64(spark, sf_dir):
    """FP64: prices against discounted prices."""
    li = table(spark, sf_dir, "lineitem").select(F.col("l_extendedprice").alias("p"), (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("q"))
    return bitdist.breakdown_of_columns(li.select(double_bits("p").alias("x"), double_bits("q").alias("y")), "x", "y")


def _tau_sql(tau: float) -> str:
    return f"e AS (SELECT * FROM (SELECT a, b, same, {DIST} FROM pe WHERE {NOT_BOTH_ZERO} GROUP BY 1, 2, 3) WHERE distance < {tau})"


@query("simgraph_edges", lambda: f"WITH {all_pairs()}, {_tau_sql(4.0)} SELECT a, b, distance FROM e")
def simgraph_edges(spark, sf_dir):
    return graph.similarity_graph(_pairwise(spark, sf_dir))


def _components(spark, sf_dir) -> tuple[DataFrame, DataFrame]:
    edges = graph.checkpointed(graph.similarity_graph(_pairwise(spark, sf_dir)))
    nodes = compared(spark, sf_dir).select(F.col("repo_id").alias("node")).distinct()
    return graph.components(nodes, edges), edges


@query("family_components", lambda: f"""WITH RECURSIVE {all_pairs()}, {_tau_sql(4.0)}, s AS (SELECT a AS u, b AS v FROM e UNION SELECT b, a FROM e),
r(node, c) AS (SELECT DISTINCT repo_id, repo_id FROM el UNION SELECT s.v, r.c FROM r JOIN s ON s.u = r.node)
SELECT node, min(c) AS component FROM r GROUP BY 1""")
def family_components(spark, sf_dir):
    """Clusters of the similarity graph."""
    return _components(spark, sf_dir)[0]


@query("cluster_quality", lambda: f"""WITH RECURSIVE {all_pairs()}, {_tau_sql(4.0)}, s AS (SELECT a AS u, b AS v FROM e UNION SELECT b, a FROM e), r(node, c) AS (SELECT DISTINCT repo_id, repo_id FROM el UNION SELECT s.v, r.c FROM r JOIN s ON s.u = r.node),
cm AS (SELECT node, min(c) AS component FROM r GROUP BY 1), tr AS (SELECT DISTINCT repo_id AS node, tf FROM el), sz AS (SELECT component, tf, count(*) AS n FROM cm JOIN tr USING (node) GROUP BY 1, 2), pu AS (SELECT max(n) AS top, sum(n) AS every FROM sz GROUP BY component),
fm AS (SELECT tf, CAST(count(*) AS DOUBLE) AS n FROM tr GROUP BY 1), po AS (SELECT sum(n * (n - 1) / 2) AS inside, sum(n) * (sum(n) - 1) / 2 AS every FROM fm), ec AS (SELECT count(*) FILTER (same) AS i, count(*) FILTER (NOT same) AS o FROM e)
SELECT round(CAST((SELECT sum(top) FROM pu) AS DOUBLE) / (SELECT sum(every) FROM pu), 6) AS purity, round(ec.i / po.inside, 6) AS within_density, round(ec.o / (po.every - po.inside), 6) AS cross_density FROM po, ec""")
def cluster_quality(spark, sf_dir):
    found, edges = _components(spark, sf_dir)
    truth = compared(spark, sf_dir).select(F.col("repo_id").alias("node"), F.col("true_family").alias("family")).distinct()
    return graph.cluster_quality(found, truth, edges)


@query("provenance_rank", lambda: f"WITH {all_pairs()}, d AS (SELECT a, b, {DIST} FROM pe WHERE {NOT_BOTH_ZERO} GROUP BY 1, 2), n AS (SELECT CASE WHEN a = 'm0_v3' THEN b ELSE a END AS candidate, distance FROM d WHERE a = 'm0_v3' OR b = 'm0_v3') SELECT 'm0_v3' AS model, candidate, distance, CAST(row_number() OVER (ORDER BY distance, candidate) AS INTEGER) AS rank FROM n ORDER BY distance, candidate LIMIT 5")
def provenance_rank(spark, sf_dir):
    return graph.provenance(_pairwise(spark, sf_dir), "m0_v3")


CLASSIFIED = ("v0", *TUNED, "v12")


@query("classify_pairs", lambda: f"""WITH {all_pairs(CLASSIFIED)}, d AS (SELECT a, b, same, {DIST} FROM pe WHERE {NOT_BOTH_ZERO} GROUP BY 1, 2, 3), m AS (SELECT DISTINCT repo_id, tf, n FROM el JOIN sg USING (family))
SELECT 'distance' AS rule, a, b, distance < 4 AS predicted, same AS actual, CAST(1 AS BIGINT) AS pairs FROM d
UNION ALL SELECT 'structure', NULL, NULL, FALSE, x.tf = y.tf, count(*) FROM m x JOIN m y ON x.repo_id < y.repo_id AND x.n <> y.n GROUP BY 5""")
def classify_pairs(spark, sf_dir):
    """Within or across the family: structure first, then the threshold.

    Pairs of equal structure are rows with their distance. Those of different structure, nearly all pairs of a large hub, are
    never made: they are counted, from the sizes of the groups of models by structure and family.
    """
    t = compared(spark, sf_dir).where(F.col("variant").isin(*CLASSIFIED))
    s = graph.signature(t).join(t.select("repo_id", F.col("true_family").alias("family")).distinct(), "repo_id")
    d = bitdist.bit_distance(graph.aligned_blocks(graph.pairs_of(s), t)).select("a", "b", "distance")
    of = lambda c: s.select(F.col("repo_id").alias(c), F.col("signature").alias(f"signature_{c}"), F.col("family").alias(f"f{c}"))
    near = family.classify_pairs(d.join(of("a"), "a").join(of("b"), "b")).select("rule", "a", "b", "predicted", (F.col("fa") == F.col("fb")).alias("actual"), F.lit(1).cast("bigint").alias("pairs"))
    return near.unionByName(family.structure_pairs(s), allowMissingColumns=True)


TAUS = [1 + 0.25 * k for k in range(29)]


def _sweep_sql(score: str, taus: list[float]) -> str:
    return f"""t AS (SELECT unnest([{', '.join(map(str, taus))}]::DOUBLE[]) AS tau), c AS (SELECT tau, count(*) FILTER ({score} < tau AND actual) AS tp, count(*) FILTER ({score} < tau AND NOT actual) AS fp, count(*) FILTER ({score} >= tau AND NOT actual) AS tn, count(*) FILTER ({score} >= tau AND actual) AS fn FROM d, t GROUP BY 1)
SELECT *, CASE WHEN tp + fp + tn + fn > 0 THEN round(CAST(tp + tn AS DOUBLE) / (tp + fp + tn + fn), 6) END AS accuracy, CASE WHEN tp + fp > 0 THEN round(CAST(tp AS DOUBLE) / (tp + fp), 6) END AS precision, CASE WHEN tp + fn > 0 THEN round(CAST(tp AS DOUBLE) / (tp + fn), 6) END AS recall, CASE WHEN 2 * tp + fp + fn > 0 THEN round(CAST(2 * tp AS DOUBLE) / (2 * tp + fp + fn), 6) END AS f1 FROM c"""


@query("threshold_sweep_zoo", lambda: f"WITH {all_pairs()}, d AS (SELECT a, b, same AS actual, {DIST} FROM pe WHERE {NOT_BOTH_ZERO} GROUP BY 1, 2, 3), " + _sweep_sql("distance", TAUS))
def threshold_sweep_zoo(spark, sf_dir):
    """Accuracy, precision, recall and F1 of the family threshold; a pair with the closely related base is across families."""
    fam = compared(spark, sf_dir).select("repo_id", F.col("true_family").alias("family")).distinct()
    d = _pairwise(spark, sf_dir).join(fam.select(F.col("repo_id").alias("a"), F.col("family").alias("fa")), "a").join(fam.select(F.col("repo_id").alias("b"), F.col("family").alias("fb")), "b")
    return family.sweep(d.withColumn("actual", F.col("fa") == F.col("fb")), TAUS)


LABEL_TAUS = [250.0 * 2**k for k in range(9)]


@query("threshold_sweep_labels", "WITH d AS (SELECT CAST(n_chars AS DOUBLE) AS distance, quality = 1 AS actual FROM documents JOIN labels USING (doc_id)), " + _sweep_sql("distance", LABEL_TAUS))
def threshold_sweep_labels(spark, sf_dir):
    """The same evaluator on a binary label with length as the score."""
    d = table(spark, sf_dir, "documents").select("doc_id", "n_chars").join(table(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id")
    return family.sweep(d.select(F.col("n_chars").cast("double").alias("distance"), (F.col("quality") == 1).alias("actual")), LABEL_TAUS)


@query("near_cross_distance", lambda: f"WITH {Z.elements(('v0', 'v12'))}, {Z.pairs('v0', ('v12',))} SELECT a, b, {DIST} FROM pe WHERE {NOT_BOTH_ZERO} GROUP BY 1, 2")
def near_cross_distance(spark, sf_dir):
    """A closely related base: a distance near the threshold."""
    return bitdist.bit_distance(blocks(spark, sf_dir, family_pairs(spark, sf_dir, ("v12",))))


GRID_W, GRID_D = [0.01, 0.015, 0.02, 0.03, 0.04, 0.05], [0.0, 0.0005, 0.001, 0.002, 0.005, 0.01, 0.02]


def _mc_sql(ws: list[float], ds: list[float]) -> str:
    d = lambda xs: "[" + ", ".join(f"CAST({x!r} AS DOUBLE)" for x in xs) + "]"
    z = zoo.noise_sql("duckdb", "'d'", "vec_id, dim")
    word = lambda x: zoo.bf16_sql("duckdb", zoo.bits32_sql("duckdb", x))
    return f"""WITH e AS (SELECT vec_id, unnest(range(len(embedding))) AS dim, CAST(unnest(embedding) AS DOUBLE) AS v FROM embeddings), f AS (SELECT * FROM e WHERE isfinite(v)),
r AS (SELECT v / (SELECT nullif(round(stddev_pop(v), 6), 0) FROM f) AS w, {z} AS d FROM f), g AS (SELECT unnest({d(ws)}) AS sigma_w), h AS (SELECT unnest({d(ds)}) AS sigma_d),
p AS (SELECT sigma_w, sigma_d, {word('sigma_w * w')} AS x, {word('sigma_w * w + sigma_d * d')} AS y FROM r, g, h)
SELECT sigma_w, sigma_d, count(*) AS n, CAST(sum(bit_count(CAST(xor(x, y) AS BIGINT))) AS BIGINT) AS bits, round(CAST(sum(bit_count(CAST(xor(x, y) AS BIGINT))) AS DOUBLE) / count(*), 6) AS expected FROM p GROUP BY 1, 2"""


def weights(spark, sf_dir) -> DataFrame:
    """(i, w): every value of the embeddings as a weight to draw, told apart by vector and place; dealt out, as the file is small."""
    e = table(spark, sf_dir, "embeddings").repartition(spark.sparkContext.defaultParallelism).select("vec_id", F.posexplode("embedding").alias("dim", "w"))
    return e.select(F.concat_ws("|", "vec_id", "dim").alias("i"), "w")


@query("mc_expected_grid", lambda: _mc_sql(GRID_W, GRID_D))
def mc_expected_grid(spark, sf_dir):
    """Expected bit distance over the sigma grid: all weights, scaled to each sigma_w, with normal noise of each sigma_d."""
    return family.expected_grid(spark, GRID_W, GRID_D, weights=weights(spark, sf_dir))


@query("mc_point", lambda: _mc_sql([0.02], [0.002]))
def mc_point(spark, sf_dir):
    return family.expected_distance(spark, 0.02, 0.002, weights=weights(spark, sf_dir))


@query("mc_generators")
def mc_generators(spark, sf_dir):
    """The same point with each normal generator."""
    w = weights(spark, sf_dir)
    made = [family.expected_distance(spark, 0.02, 0.002, generator=g, weights=w).withColumn("generator", F.lit(g)) for g in ("md5", "box_muller", "randn")]
    return made[0].unionAll(made[1]).unionAll(made[2])


@query("empirical_sigmas", lambda: f"WITH {Z.elements(('v0', *TUNED))}, {Z.pairs()} SELECT family, variant, round(stddev_pop({Z.VALUE.format(b='x')}), 6) AS sigma_w, round(stddev_pop({DW}), 6) AS sigma_d FROM pe GROUP BY 1, 2")
def empirical_sigmas(spark, sf_dir):
    return family.empirical_sigmas(zoo.elements(spark, sf_dir))


# --- Lineage and matching -----------------------------------------------------------------------------------------

REPOS = "VALUES " + ", ".join(f"('{v}')" for v in zoo.VARIANTS)
LINEAGE = f"""fm AS (SELECT DISTINCT label AS family FROM embeddings), vr AS (SELECT * FROM ({REPOS}) t(variant)), rp AS (SELECT 'm' || family || '_' || variant AS repo_id, family, variant FROM fm, vr),
lg AS (SELECT repo_id, CASE WHEN variant IN ('v0', 'v12', 'v13') THEN 'ambiguous' WHEN variant = 'v8' THEN 'missing' ELSE 'exact' END AS status, CASE WHEN variant IN ('v0', 'v12', 'v13', 'v8') THEN NULL WHEN variant = 'v12c' THEN 'm' || family || '_v12' ELSE 'm' || family || '_v0' END AS base,
 CASE WHEN variant = 'v8' THEN NULL WHEN variant IN ('v0', 'v12') THEN 'config' WHEN variant = 'v13' THEN CASE WHEN family % 2 = 1 THEN 'card family' ELSE 'config' END ELSE 'card' END AS source FROM rp)"""


@query("lineage_cards", f"WITH {LINEAGE} SELECT repo_id, status, base, source FROM lg")
def lineage_cards(spark, sf_dir):
    """Declared bases from cards and configs; broken front matter counts as missing."""
    return family.from_metadata(zoo.repos(spark, sf_dir)).select("repo_id", "status", "base", "source")


@query("lineage_benchmark", "SELECT doc_id, item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)")
def lineage_benchmark(spark, sf_dir):
    """Documents derived from known items: those that contain an item verbatim.

    An item's second to fourth word stand in a document as they are wherever the item does; their hash is looked up among
    the document's word triples, and only hits are checked for the whole item. Items are dealt in parts, each with a scan of
    its own, as their hashes go into the plan; items of fewer than five words are looked for directly.
    """
    w = F.split(F.trim("item"), r"\s+")
    items = table(spark, sf_dir, "benchmark").select("item_id", F.col("text").alias("item")).where("length(trim(item)) > 0").distinct().withColumn("w", w)
    docs = table(spark, sf_dir, "documents").select("doc_id", "text").where("text IS NOT NULL").withColumn("w", F.split("text", r"\s+"))
    parts = max(1, -(-5 * items.count() // (4 * ITEMS_A_SCAN)))
    part = F.pmod(F.xxhash64("item_id", "item"), F.lit(parts))
    return reduce(DataFrame.unionAll, [_items_in(docs, items.where(part == k)) for k in range(parts)]).distinct()


#: Items that one scan of the documents looks up, about.
ITEMS_A_SCAN = 10_000


def _items_in(docs: DataFrame, items: DataFrame) -> DataFrame:
    """(doc_id, item_id) of one part of the items."""
    head = items.where(F.size("w") >= 5).select("item_id", "item", F.xxhash64(F.col("w")[1], F.col("w")[2], F.col("w")[3]).alias("h"))
    known = sorted({r["h"] for r in head.select("h").distinct().collect()})
    short = [(r["item_id"], r["item"]) for r in items.where(F.size("w") < 5).collect()]
    triple = lambda i: F.xxhash64(F.get("w", i), F.get("w", i + 1), F.get("w", i + 2))
    at = F.filter(F.transform(F.sequence(F.lit(0), F.size("w") - 3), triple), lambda h: h.isin(known))
    hits = docs.where(F.size("w") >= 3).select("doc_id", "text", F.explode(F.array_distinct(at)).alias("h"))
    found = hits.join(F.broadcast(head), "h").where(F.contains("text", "item")).select("doc_id", "item_id")
    for item_id, item in short:
        found = found.unionAll(docs.where(F.contains("text", F.lit(item))).select("doc_id", F.lit(item_id).cast("bigint").alias("item_id")))
    return found


def _open_models(spark, sf_dir) -> tuple[DataFrame, DataFrame, DataFrame]:
    t = zoo.tensors(spark, sf_dir).where(F.col("variant").isin("v0", "v12", "v13"))
    s = graph.signature(t).join(t.select("repo_id", F.concat(F.lit("m"), F.col("family").cast("string")).alias("family"), "variant").distinct(), "repo_id")
    return t, s.where("variant = 'v13'"), s.where("variant <> 'v13'")


@query("nearest_base", lambda: f"""WITH {Z.elements(('v0', 'v12', 'v13'))}, sg AS (SELECT family, count(*) AS n FROM el WHERE variant = 'v0' GROUP BY 1),
cd AS (SELECT m.repo_id AS model, b.repo_id AS base FROM (SELECT DISTINCT repo_id, family, variant FROM el) m JOIN sg s USING (family) JOIN sg q ON q.n = s.n JOIN (SELECT DISTINCT repo_id, family, variant FROM el) b ON b.family = q.family WHERE m.variant = 'v13' AND b.variant <> 'v13'),
pe AS (SELECT cd.model, cd.base, p.bits AS x, q.bits AS y FROM cd JOIN el p ON p.repo_id = cd.model JOIN el q ON q.repo_id = cd.base AND p.ordinal = q.ordinal AND p.idx = q.idx),
d AS (SELECT model, base, {DIST} FROM pe WHERE {NOT_BOTH_ZERO} GROUP BY 1, 2), o AS (SELECT *, row_number() OVER (PARTITION BY model ORDER BY distance, base) AS r FROM d)
SELECT x.model, CASE WHEN x.distance < 4 THEN x.base END AS base, x.distance, y.distance AS runner_up, round(y.distance - x.distance, 6) AS margin, x.distance < 4 AS within FROM o x LEFT JOIN o y ON y.model = x.model AND y.r = 2 WHERE x.r = 1""")
def nearest_base(spark, sf_dir):
    """Models without an exact card: the closest base among all of like structure."""
    t, models, bases = _open_models(spark, sf_dir)
    return family.nearest_base(family.match_distances(family.candidate_bases(models, bases), t), tau=4.0)


@query("partial_match", lambda: f"WITH {Z.tensors(('v0', 'v5', 'v9'))}, m AS (SELECT x.repo_id AS model, y.repo_id AS base, count(*) AS shared FROM tn x JOIN tn y ON x.ordinal = y.ordinal AND x.dtype = y.dtype AND x.shape = y.shape AND x.repo_id <> y.repo_id WHERE x.variant <> 'v0' AND y.variant = 'v0' GROUP BY 1, 2) SELECT model, base, round(CAST(shared AS DOUBLE) / n, 6) AS shared_share FROM m JOIN (SELECT repo_id AS model, count(*) AS n FROM tn GROUP BY 1) USING (model)")
def partial_match(spark, sf_dir):
    """Shares of tensors with a twin in a base, for models with an expanded or mixed-precision tensor."""
    t = zoo.tensors(spark, sf_dir).drop("payload")
    return family.shared_share(t.where("variant IN ('v5', 'v9')"), t.where("variant = 'v0'"))


DECLARED = ("v0", "v1", "v2", "v3", "v4", "v5", "v6", "v7", "v9", "v12", "v12c")


@query("lineage_conflicts", lambda: f"""WITH {Z.tensors(DECLARED)}, nw AS (SELECT family, ordinal, row_number() OVER (PARTITION BY family ORDER BY name) - 1 AS o6 FROM tn WHERE variant = 'v6'), sz AS (SELECT repo_id, ordinal, n_elems FROM tn),
x AS (SELECT el.repo_id, el.family, variant, el.ordinal AS old, CASE WHEN variant = 'v6' THEN o6 ELSE el.ordinal END AS ordinal, idx, dtype, bits, n_elems FROM el JOIN nw ON nw.family = el.family AND nw.ordinal = el.ordinal JOIN sz ON sz.repo_id = el.repo_id AND sz.ordinal = el.ordinal),
pe AS (SELECT p.repo_id AS a, q.repo_id AS b, p.bits AS x, q.bits AS y FROM x p JOIN x q ON q.family = p.family AND q.variant = CASE WHEN p.variant = 'v12c' THEN 'v12' ELSE 'v0' END AND q.ordinal = p.ordinal AND q.idx = p.idx AND q.dtype = p.dtype AND q.n_elems = p.n_elems WHERE p.variant NOT IN ('v0', 'v12')),
d AS (SELECT a, b, {DIST} FROM pe WHERE {NOT_BOTH_ZERO} GROUP BY 1, 2) SELECT a, b, distance, distance >= 4.0 AS conflict FROM d""")
def lineage_conflicts(spark, sf_dir):
    """Declared bases that bit distance contradicts."""
    told = family.from_metadata(zoo.repos(spark, sf_dir)).where("status = 'exact'").select(F.col("repo_id").alias("a"), F.col("base").alias("b"))
    return bitdist.bit_distance(blocks(spark, sf_dir, told)).select("a", "b", "distance", (F.col("distance") >= 4.0).alias("conflict"))


@query("dtype_bytes_vs_models", lambda: f"WITH {Z.tensors()} SELECT dtype, count(DISTINCT repo_id) AS models, CAST(sum(n_bytes) AS BIGINT) AS bytes, round(CAST(sum(n_bytes) AS DOUBLE) / (SELECT sum(n_bytes) FROM tn), 6) AS byte_share FROM tn GROUP BY 1")
def dtype_bytes_vs_models(spark, sf_dir):
    """dtypes by bytes and by models; a model of several dtypes counts in each."""
    t = zoo.tensors(spark, sf_dir).where(F.col("variant").isin(*Z.ORDERED)).select("repo_id", "dtype", "n_bytes")
    d = t.groupBy("dtype").agg(F.count_distinct("repo_id").alias("models"), F.sum("n_bytes").alias("bytes"))
    return d.crossJoin(t.agg(F.sum("n_bytes").alias("all"))).select("dtype", "models", "bytes", F.round(F.col("bytes") / F.col("all"), 6).alias("byte_share"))


@query("base_vs_tuned_share", lambda: f"WITH {Z.tensors()}, g AS (SELECT CASE WHEN variant IN ('v0', 'v12') THEN 'base' ELSE 'tuned' END AS kind, count(DISTINCT repo_id) AS models, CAST(sum(n_bytes) AS BIGINT) AS bytes FROM tn GROUP BY 1) SELECT kind, models, bytes, round(CAST(models AS DOUBLE) / sum(models) OVER (), 6) AS model_share, round(CAST(bytes AS DOUBLE) / sum(bytes) OVER (), 6) AS byte_share FROM g")
def base_vs_tuned_share(spark, sf_dir):
    t = zoo.tensors(spark, sf_dir).where(F.col("variant").isin(*Z.ORDERED)).select("repo_id", F.when(F.col("variant").isin("v0", "v12"), "base").otherwise("tuned").alias("kind"), "n_bytes")
    g = t.groupBy("kind").agg(F.count_distinct("repo_id").alias("models"), F.sum("n_bytes").alias("bytes"))
    return g.crossJoin(g.agg(F.sum("models").alias("m"), F.sum("bytes").alias("b"))).select("kind", "models", "bytes", F.round(F.col("models") / F.col("m"), 6).alias("model_share"), F.round(F.col("bytes") / F.col("b"), 6).alias("byte_share"))


@query("adapter_filter", f"WITH {LINEAGE} SELECT repo_id, variant = 'v11' AS adapter FROM rp")
def adapter_filter(spark, sf_dir):
    from xorvault.plans import hub

    return hub.is_adapter(zoo.tensors(spark, sf_dir).drop("payload"))


@query("naming_audit", lambda: f"""WITH {Z.tensors(('v0', 'v2', 'v5', 'v6'))}, t AS (SELECT family, variant, repo_id, CASE WHEN variant = 'v6' THEN row_number() OVER (PARTITION BY family, variant ORDER BY 'model.' || name) - 1 ELSE ordinal END AS ordinal, CASE WHEN variant = 'v6' THEN 'model.' || name ELSE name END AS name, name AS nn, dtype, shape FROM tn WHERE variant <> 'v0'),
g AS (SELECT repo_id, family, count(*) AS n_tensors, list(name ORDER BY ordinal) = list(name ORDER BY name) AS alphabetical FROM t GROUP BY 1, 2),
m AS (SELECT t.repo_id, count(*) FILTER (t.ordinal = b.ordinal) AS by_order, count(*) FILTER (t.name = b.name) AS by_name, count(*) FILTER (t.nn = b.name) AS by_normalized FROM t JOIN tn b ON b.variant = 'v0' AND b.family = t.family AND b.dtype = t.dtype AND b.shape = t.shape GROUP BY 1),
o AS (SELECT g.repo_id, 'm' || family || '_v0' AS base_repo, n_tensors, alphabetical, coalesce(by_order, 0) AS by_order, coalesce(by_name, 0) AS by_name, coalesce(by_normalized, 0) AS by_normalized FROM g LEFT JOIN m USING (repo_id))
SELECT *, CASE WHEN by_normalized > by_name THEN 'renamed' WHEN by_name > by_order THEN 'reordered' ELSE 'aligned' END AS finding FROM o""")
def naming_audit(spark, sf_dir):
    """Archives whose naming or order hides their twins."""
    t = zoo.tensors(spark, sf_dir).drop("payload")
    tuned = t.where("variant IN ('v2', 'v5', 'v6')").withColumn("base_repo", F.concat(F.lit("m"), F.col("family").cast("string"), F.lit("_v0")))
    return align.naming_audit(tuned, t.where("variant = 'v0'"))


@query("timeseries_xor", """WITH w AS (SELECT user_id, event_id, CAST(CAST(value AS BIT) AS BIGINT) AS x FROM events), d AS (SELECT user_id, xor(x, lag(x) OVER (PARTITION BY user_id ORDER BY event_id)) AS d FROM w)
SELECT user_id, count(*) AS n, count(*) FILTER (d = 0) AS zero_xors, CAST(coalesce(sum(bit_count(d)), 0) AS BIGINT) AS one_bits FROM d GROUP BY 1""")
def timeseries_xor(spark, sf_dir):
    return timeseries.consecutive_xor(table(spark, sf_dir, "events"), by="user_id", order="event_id", value="value")
