"""The storage reduction pipeline: file deduplication, tensor pool, families, delta coding, manifests; restore, fallback, collection.

Order: files that are exact copies go first; of the others every tensor is hashed, and one of each kind is pooled;
models get a base from their card, or by the least bit distance among candidates of like structure; pooled tensors of
tuned models are stored as the XOR against the aligned base tensor, quantized ones as the recipe that makes them from it, and
others (adapters among them) by the smallest standalone coder. Only hashes,
sizes and references are shuffled before the last step, which joins payloads once.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from xorvault.operators import align, bitdist, codecs, dedup, family, graph


@dataclass(frozen=True)
class Config:
    codec: str = "zstd"
    level: int = 3
    transform: str = "xor"
    plane_split: bool = False
    standalone: tuple[str, ...] = ("zstd", "grouping_huffman")
    alignment: str = "order"
    choose_smaller: bool = True
    tau: float | None = None


@dataclass
class HubStore:
    """pool: one row per stored tensor with its coded payload. manifests: one row per tensor of each model, in file order.
    links: models that are exact copies, and of which. lineage: each model's base."""

    pool: DataFrame
    manifests: DataFrame
    links: DataFrame
    lineage: DataFrame
    config: Config = field(default_factory=Config)

    def report(self) -> DataFrame:
        """(repo_id, n_raw, n_stored, drr): a pooled tensor is paid for by the model that brought it first."""
        raw = self.manifests.groupBy("repo_id").agg(F.sum("n_bytes").alias("n_raw"))
        linked = self.links.groupBy("repo_id").agg(F.sum("n_bytes").alias("linked"))
        stored = self.pool.groupBy(F.col("first_repo").alias("repo_id")).agg(F.sum("n_stored").alias("n_stored"))
        joined = raw.join(linked, "repo_id", "full_outer").join(stored, "repo_id", "left")
        n = F.coalesce("n_raw", "linked").alias("n_raw")
        return joined.select("repo_id", n, F.coalesce("n_stored", F.lit(0)).cast("bigint").alias("n_stored")).withColumn("drr", F.round(1 - F.col("n_stored") / F.col("n_raw"), 6))

    def written(self, path: str, files: int = 16) -> HubStore:
        """The store as Parquet under `path`, pool and manifests ranged by hash, and read back from there."""
        spark = self.pool.sparkSession
        self.pool.repartitionByRange(files, "tensor_hash").sortWithinPartitions("tensor_hash").write.mode("overwrite").parquet(f"{path}/pool")
        for name in ("manifests", "links", "lineage"):
            getattr(self, name).write.mode("overwrite").parquet(f"{path}/{name}")
        return HubStore(*[spark.read.parquet(f"{path}/{n}") for n in ("pool", "manifests", "links", "lineage")], self.config)


def is_adapter(tensors: DataFrame) -> DataFrame:
    """(repo_id, adapter): repositories all of whose tensors are low-rank factors."""
    return tensors.groupBy("repo_id").agg(F.bool_and(F.col("name").rlike(r"(^|\.)lora_")).alias("adapter"))


def route(files: DataFrame) -> DataFrame:
    """Files with `route`: tensors for parsed archives, quantized, opaque for legacy formats, aux for the rest."""
    ext = F.lower(F.regexp_extract("path", r"\.([A-Za-z0-9]+)$", 1))
    kind = F.when(ext.isin("tensors", "safetensors"), "tensors").when(ext.isin("gguf", "qtensors"), "quantized").when(ext.isin("bin", "h5", "pt", "pth", "ckpt"), "opaque").otherwise("aux")
    return files.withColumn("route", kind)


def assign_bases(tensors: DataFrame, live: DataFrame, repos: DataFrame, config: Config) -> DataFrame:
    """(repo_id, base, source): from the card where it names an existing base, else by the least bit distance.

    `live` has the models that are stored, not linked; payloads are read of candidate pairs alone.
    """
    told = family.from_metadata(repos)
    exact = told.where("status = 'exact'").select("repo_id", "base", F.lit("card").alias("source"))
    signatures = graph.signature(tensors.drop("payload")).join(told.select("repo_id", "family"), "repo_id")
    roots = exact.select(F.col("base").alias("repo_id")).distinct()
    open_models = signatures.join(live, "repo_id", "left_semi").join(exact, "repo_id", "left_anti").join(roots, "repo_id", "left_anti")
    found = family.nearest_base(family.match_distances(family.candidate_bases(open_models, signatures.join(roots, "repo_id")), tensors), tau=config.tau)
    return exact.unionAll(found.where("base IS NOT NULL").select(F.col("model").alias("repo_id"), "base", F.lit("distance").alias("source")))


#: Children of one base that a task gets together with it.
CHILDREN_A_TASK = 64
#: Parts that the children of one base are dealt to when they are told its count.
SALTS = 16


def with_bases(children: DataFrame, payloads: DataFrame, bases: DataFrame, *, own: list[str], base: list[str]) -> DataFrame:
    """children (metadata, all of which name a base) with their payload columns by `own`, and the row of `bases` they name.

    One base may have any share of all children, so its row is sent to as many tasks as its children fill; children learn
    that count, and take a part, before any payload is fetched. Children without a base don't belong here: with a null
    key, they would all meet in one task.
    """
    children = graph.checkpointed(children)
    counts = graph.checkpointed(children.groupBy(*base).agg(F.ceil(F.count("*") / CHILDREN_A_TASK).cast("int").alias("_parts")))
    salted = counts.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    dealt = children.withColumn("_salt", F.pmod(F.xxhash64(*own), F.lit(SALTS)).cast("int")).join(salted, [*base, "_salt"])
    dealt = dealt.withColumn("_part", F.pmod(F.xxhash64(F.lit(7), *own), "_parts").cast("int")).drop("_salt", "_parts")
    sent = bases.join(counts, base).withColumn("_part", F.explode(F.sequence(F.lit(0), F.col("_parts") - 1))).drop("_parts")
    return dealt.join(payloads, own).join(sent, [*base, "_part"], "left").drop("_part")


def reduce_hub(tensors: DataFrame, repos: DataFrame, *, config: Config = Config(), after: HubStore | None = None, bases: DataFrame | None = None) -> HubStore:
    """The whole pipeline over tensors (with payload) and repos (card, config, seq).

    With `after`, the tensors are later uploads to that store: files and tensors that it has become links and references,
    and the result holds both. `repos` then has earlier and new repositories, and `bases` the earlier tensors (with
    payload) that may serve as bases.
    """
    order, meta = repos.select("repo_id", "seq"), tensors.drop("payload")
    readable = tensors if bases is None else tensors.unionByName(bases.select(*tensors.columns))
    # 1. Files that are copies become links.
    files = dedup.files_of(meta).join(order, "repo_id").withColumnRenamed("unit_hash", "file_hash")
    earlier = None
    if after is not None:
        held = dedup.files_of(after.manifests).groupBy(F.col("unit_hash").alias("file_hash")).agg(F.min(F.struct("repo_id", "path")).alias("of"))
        earlier = files.join(held, "file_hash").select("repo_id", "path", "n_bytes", F.col("of.repo_id").alias("of_repo"), F.col("of.path").alias("of_path"))
        files = files.join(held, "file_hash", "left_anti")
    marked = dedup.dedup_files(files, order_by=("seq", "repo_id", "path"))
    unique, copies = dedup.split_unique(marked)
    links = copies.select("repo_id", "path", "n_bytes", F.col("canonical.repo_id").alias("of_repo"), F.col("canonical.path").alias("of_path"))
    links = links if earlier is None else links.unionAll(earlier)
    # 2. One of each tensor is pooled: the first in upload order.
    kept = meta.join(unique.select("repo_id", "path", "seq"), ["repo_id", "path"]).withColumn("pool_key", dedup.tensor_identity())
    first = kept.groupBy("pool_key").agg(F.min(F.struct("seq", "repo_id", "path", "ordinal")).alias("f"), F.count("*").alias("refcount"))
    first = first if after is None else first.join(after.pool.select("pool_key"), "pool_key", "left_anti")
    pooled = kept.join(first, "pool_key").where("f.repo_id = repo_id AND f.path = path AND f.ordinal = ordinal")
    # 3. Bases; only candidate pairs' payloads are read.
    lineage = assign_bases(readable, unique.select("repo_id").distinct(), repos, config)
    # 4. What is pooled is paired with its base's tensor, and then, for the first time, bytes are fetched.
    base_of = lineage.select("repo_id", F.col("base").alias("base_repo"))
    roots = readable.drop("payload").join(base_of.select(F.col("base_repo").alias("repo_id")).distinct(), "repo_id", "left_semi")
    if after is not None:  # a tensor that is a delta already can't be a base
        roots = roots.join(after.pool.where("base_hash IS NOT NULL").select("tensor_hash"), "tensor_hash", "left_anti")
    # What any model's base has is stored on its own, whoever brought it first, so that no chain is longer than one.
    own = roots.select("tensor_hash").distinct().withColumn("is_base", F.lit(True))
    deltas = pooled.join(own, "tensor_hash", "left").join(base_of, "repo_id", "left").withColumn("base_repo", F.when(F.col("is_base").isNull(), F.col("base_repo")))
    paired = align.align(deltas, roots, by=config.alignment)
    payloads = tensors.select("repo_id", "path", "ordinal", "payload")
    base_bytes = readable.select(F.col("repo_id").alias("base_repo"), F.col("path").alias("base_path"), F.col("ordinal").alias("base_ordinal"), F.col("dtype").alias("base_dtype"), F.col("payload").alias("payload_b"))
    paired, own_key, base_key = graph.checkpointed(align.align_recipes(paired, roots)), ["repo_id", "path", "ordinal"], ["base_repo", "base_path", "base_ordinal"]
    known = F.col("base_path").isNotNull() & F.col("base_ordinal").isNotNull()
    aligned = with_bases(paired.where(known), payloads, base_bytes, own=own_key, base=base_key).unionByName(paired.where(~known).join(payloads, own_key), allowMissingColumns=True)

    def make(payload, base, dtype, base_dtype):
        if base is not None and base_dtype != dtype:
            data = codecs.recipe_encode(payload, base, base_dtype) or codecs.smallest(payload, dtype, config.standalone)
            return {"coded": data, "n_stored": len(data), "codec": codecs.codec_of(data)}
        options = {"transform": config.transform, "codec": config.codec, "level": config.level, "plane_split": config.plane_split}
        alone = codecs.smallest(payload, dtype, config.standalone) if base is None or config.choose_smaller else None
        data = codecs.delta_encode(payload, base, dtype, **options) if base is not None else alone
        if alone is not None and len(alone) < len(data):
            data = alone
        return {"coded": data, "n_stored": len(data), "codec": codecs.codec_of(data)}

    keep = ["pool_key", "tensor_hash", "dtype", "shape", "n_bytes", "refcount", "repo_id", "base_hash"]
    coded = codecs.on_rows(aligned, keep, ["payload", "payload_b", "dtype", "base_dtype"], make, "coded binary, n_stored bigint, codec string")
    uses_base = F.col("codec").isin("xor", "xor_planes", "wrap", "zigzag", "recipe")
    pool = coded.withColumn("base_hash", F.when(uses_base, F.col("base_hash"))).withColumnRenamed("repo_id", "first_repo")
    manifests = kept.select("repo_id", "path", "ordinal", "name", "dtype", "shape", "offset", "n_bytes", "tensor_hash", "pool_key")
    new = HubStore(pool, manifests, links, lineage, config)
    if after is None:
        return new
    return HubStore(*[getattr(after, n).unionByName(getattr(new, n)) for n in ("pool", "manifests", "links", "lineage")], config)


def compact(store: HubStore, path: str, *, target_bytes: int = 128 << 20) -> HubStore:
    """The store rewritten with pool files of about target_bytes, ranged by hash."""
    total = store.pool.agg(F.sum("n_stored").alias("n")).first()["n"] or 0
    return store.written(path, files=max(1, -(-total // target_bytes)))


def decoded_pool(pool: DataFrame) -> DataFrame:
    """Pool rows with their raw payload; a base is always stored on its own, so one join finds it, which tensors without one skip."""
    alone = pool.where("base_hash IS NULL")
    bases = alone.join(pool.where("base_hash IS NOT NULL").select(F.col("base_hash").alias("tensor_hash")).distinct(), "tensor_hash", "left_semi").select(F.col("tensor_hash").alias("base_hash"), F.col("coded").alias("base_coded"), F.col("dtype").alias("base_dtype")).dropDuplicates(["base_hash"])
    deltas = pool.where("base_hash IS NOT NULL")
    both = with_bases(deltas.select("pool_key", "base_hash"), deltas.drop("base_hash"), bases, own=["pool_key"], base=["base_hash"]).unionByName(alone, allowMissingColumns=True)

    def make(data, dtype, base, base_dtype):
        return {"payload": codecs.decode(data, dtype, codecs.decode(base, base_dtype) if base is not None else None)}

    return codecs.on_rows(both, ["pool_key", "dtype"], ["coded", "dtype", "base_coded", "base_dtype"], make, "payload binary")


def restore(store: HubStore, repo_ids: list[str] | None = None) -> DataFrame:
    """(repo_id, path, ordinal, offset, dtype, tensor_hash, payload) of whole models, links followed."""
    links = store.links.select(F.col("repo_id").alias("to_repo"), F.col("path").alias("to_path"), F.col("of_repo").alias("repo_id"), F.col("of_path").alias("path"))
    own = store.manifests.withColumns({"to_repo": F.col("repo_id"), "to_path": F.col("path")})
    every = own.unionByName(store.manifests.join(links, ["repo_id", "path"]))
    if repo_ids is not None:
        every = every.where(F.col("to_repo").isin(repo_ids))
    needed = every.select("pool_key").distinct() if repo_ids is not None else None
    pool = store.pool
    if needed is not None:
        wanted = pool.join(needed, "pool_key", "left_semi")
        bases = pool.join(wanted.select(F.col("base_hash").alias("tensor_hash")).where("tensor_hash IS NOT NULL").distinct(), "tensor_hash", "left_semi")
        pool = wanted.unionByName(bases.join(needed, "pool_key", "left_anti"))
    raw = decoded_pool(pool).select("pool_key", "payload")
    return every.join(raw, "pool_key").select(F.col("to_repo").alias("repo_id"), F.col("to_path").alias("path"), "ordinal", "name", "offset", "dtype", "shape", "n_bytes", "tensor_hash", "payload")


def verify(restored: DataFrame, originals: DataFrame) -> DataFrame:
    """(repo_id, path, n_bytes, sha256, ok) per file: the digest covers tensor digests in file order."""

    def digest(df: DataFrame) -> DataFrame:
        each = df.select("repo_id", "path", "ordinal", F.length("payload").alias("n"), F.sha2("payload", 256).alias("h"))
        in_order = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("ordinal", "h"))), lambda x: x["h"]), "")
        return each.groupBy("repo_id", "path").agg(F.sum("n").alias("n_bytes"), F.sha2(in_order, 256).alias("sha256"))

    got, want = digest(restored), digest(originals).select("repo_id", "path", F.col("sha256").alias("want"))
    return want.join(got, ["repo_id", "path"], "left").select("repo_id", "path", "n_bytes", "sha256", F.coalesce(F.col("sha256") == F.col("want"), F.lit(False)).alias("ok"))


def write_files(restored: DataFrame, headers: DataFrame, path: str) -> DataFrame:
    """(repo_id, path, n_bytes) of restored archives, written under a folder that all executors share.

    Rows come sorted by offset within their file and are appended as they come, so no file is held whole.
    """
    import os

    ordered = restored.join(headers, ["repo_id", "path"]).repartition("repo_id", "path").sortWithinPartitions("repo_id", "path", "offset")

    def run(batches):
        done: dict[tuple, int] = {}
        for batch in batches:
            for r in batch.select(["repo_id", "path", "header", "payload"]).to_pylist():
                key = (r["repo_id"], r["path"])
                at = os.path.join(path, *key)
                os.makedirs(os.path.dirname(at), exist_ok=True)
                with open(at, "ab" if key in done else "wb") as f:
                    if key not in done:
                        f.write(r["header"])
                        done[key] = len(r["header"])
                    f.write(r["payload"])
                done[key] += len(r["payload"])
        yield pa.RecordBatch.from_pylist([{"repo_id": a, "path": b, "n_bytes": n} for (a, b), n in done.items()], schema=pa.schema([("repo_id", pa.string()), ("path", pa.string()), ("n_bytes", pa.int64())]))

    return ordered.mapInArrow(run, "repo_id string, path string, n_bytes bigint")


# --- Fallbacks and collection -------------------------------------------------------------------------------------


def substitute_copy(lost: str, files: DataFrame) -> DataFrame:
    """(lost, substitute) where another repository holds an identical file set."""
    gone = files.where(F.col("repo_id") == lost).select("unit_hash")
    return files.join(gone, "unit_hash", "left_semi").where(F.col("repo_id") != lost).agg(F.min("repo_id").alias("substitute")).select(F.lit(lost).alias("lost"), "substitute")


def surrogate(tensors: DataFrame, lost: str, children: list[str]) -> DataFrame:
    """(surrogate, distance): the tuned model closest to the lost base while it can still be read."""
    spark = tensors.sparkSession
    pairs = spark.createDataFrame([(lost, c) for c in children], "a string, b string")
    return bitdist.bit_distance(graph.aligned_blocks(pairs, tensors)).orderBy("distance", "b").limit(1).select(F.col("b").alias("surrogate"), "distance")


def surrogate_plan(tensors: DataFrame, lost: str, surrogate_repo: str, children: list[str], config: Config = Config()) -> DataFrame:
    """(mode, repo_id, ordinal, n_raw, n_stored, ok) for three ways to live without the lost base.

    mask: the XOR of surrogate and base is stored once per tensor, and children keep their deltas. rebase: each child is
    coded anew against the surrogate. standalone: each child is coded on its own. `ok` tells that decoding is exact.
    """
    by = lambda r, c: tensors.where(F.col("repo_id") == r).select("ordinal", F.col("payload").alias(c))
    kids = tensors.where(F.col("repo_id").isin(children) & (F.col("repo_id") != surrogate_repo))
    both = kids.join(by(lost, "base"), "ordinal").join(by(surrogate_repo, "stand_in"), "ordinal")

    def child(payload, base, stand_in, dtype):
        rebased = codecs.delta_encode(payload, stand_in, dtype, codec=config.codec, level=config.level)
        alone = codecs.smallest(payload, dtype, config.standalone)
        masked = codecs.W.xor(stand_in, base)
        kept = codecs.W.xor(payload, base)
        return {"modes": [{"mode": "mask", "n_stored": 0, "ok": codecs.W.xor(codecs.W.xor(kept, masked), stand_in) == payload}, {"mode": "rebase", "n_stored": len(rebased), "ok": codecs.decode(rebased, dtype, stand_in) == payload}, {"mode": "standalone", "n_stored": len(alone), "ok": codecs.decode(alone, dtype) == payload}], "n_raw": len(payload)}

    kind = "modes array<struct<mode: string, n_stored: bigint, ok: boolean>>, n_raw bigint"
    rows = codecs.on_rows(both, ["repo_id", "ordinal"], ["payload", "base", "stand_in", "dtype"], child, kind).select("repo_id", "ordinal", "n_raw", F.inline("modes"))

    def mask(base, stand_in, dtype):
        data = codecs.delta_encode(base, stand_in, dtype, codec=config.codec, level=config.level)
        return {"n_raw": 0, "mode": "mask", "n_stored": len(data), "ok": codecs.decode(data, dtype, stand_in) == base}

    once = tensors.where(F.col("repo_id") == lost).select("ordinal", "dtype", F.col("payload").alias("base")).join(by(surrogate_repo, "stand_in"), "ordinal").withColumn("repo_id", F.lit(lost))
    masks = codecs.on_rows(once, ["repo_id", "ordinal"], ["base", "stand_in", "dtype"], mask, "n_raw bigint, mode string, n_stored bigint, ok boolean")
    return rows.unionByName(masks)


def choose_smaller(plans: DataFrame) -> DataFrame:
    """(mode, n_stored): the way with the fewest new bytes."""
    total = plans.groupBy("mode").agg(F.sum("n_stored").alias("n_stored"), F.bool_and("ok").alias("ok"))
    return total.where("ok").orderBy("n_stored", "mode").limit(1).select("mode", "n_stored")


def refcounts(store: HubStore) -> DataFrame:
    """(pool_key, tensor_hash, n_manifest, n_delta): references from manifests and from deltas."""
    m = store.manifests.groupBy("pool_key").agg(F.count("*").alias("n_manifest"))
    d = store.pool.where("base_hash IS NOT NULL").groupBy(F.col("base_hash").alias("tensor_hash")).agg(F.count("*").alias("n_delta"))
    return store.pool.select("pool_key", "tensor_hash").join(m, "pool_key", "left").join(d, "tensor_hash", "left").fillna(0, ["n_manifest", "n_delta"])


def collect_garbage(store: HubStore, removed: list[str]) -> tuple[HubStore, DataFrame]:
    """The store without the removed models' manifests and unreferenced tensors, and (pool_key, fate) of what they used.

    A tensor goes if no manifest, link or delta refers to it; one that only deltas refer to is kept as `base only`.
    """
    manifests = store.manifests.where(~F.col("repo_id").isin(removed)) if removed else store.manifests
    held = store.links.where(~F.col("repo_id").isin(removed)).select(F.col("of_repo").alias("repo_id"), F.col("of_path").alias("path")).distinct()
    manifests = manifests.unionByName(store.manifests.where(F.col("repo_id").isin(removed)).join(held, ["repo_id", "path"], "left_semi"))
    m = manifests.groupBy("pool_key").agg(F.count("*").alias("n_manifest"))
    alive = store.pool.join(m.select("pool_key"), "pool_key", "left_semi")
    used = alive.where("base_hash IS NOT NULL").select(F.col("base_hash").alias("tensor_hash")).distinct().withColumn("as_base", F.lit(True))
    fate = store.pool.select("pool_key", "tensor_hash", "base_hash").join(m, "pool_key", "left").join(used, "tensor_hash", "left").select("pool_key", F.when(F.col("n_manifest").isNotNull(), "kept").when(F.col("as_base"), "base only").otherwise("collected").alias("fate"))
    left = store.pool.join(fate.where("fate <> 'collected'").select("pool_key"), "pool_key", "left_semi")
    return HubStore(left, manifests, store.links.where(~F.col("repo_id").isin(removed)), store.lineage, store.config), fate


def integrity(store: HubStore) -> DataFrame:
    """(pool_key, ok): every pooled tensor decodes to bytes with its own hash."""
    raw = decoded_pool(store.pool)
    return raw.join(store.pool.select("pool_key", "tensor_hash"), "pool_key").select("pool_key", (F.sha2("payload", 256) == F.col("tensor_hash")).alias("ok"))


def chain(pool: DataFrame, max_depth: int = 4) -> DataFrame:
    """(tensor_hash, depth): how many bases a tensor needs to be decoded; more than max_depth is an error."""
    at = pool.select("tensor_hash", F.col("base_hash").alias("next"), F.lit(0).alias("depth"))
    link = pool.select(F.col("tensor_hash").alias("next"), F.col("base_hash").alias("after")).dropDuplicates(["next"])
    for k in range(max_depth):
        at = at.join(link, "next", "left").select("tensor_hash", F.col("after").alias("next"), F.when(F.col("next").isNotNull(), k + 1).otherwise(F.col("depth")).alias("depth"))
    return at.select("tensor_hash", F.when(F.col("next").isNotNull(), F.raise_error(F.lit("delta chain too deep")).cast("int")).otherwise(F.col("depth")).alias("depth"))


