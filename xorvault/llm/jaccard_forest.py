"""Joining documents on the Jaccard similarity of their word n-grams with a MinHash LSH forest.

Texts with the same words form one class of copies and take part once. A text's signature has a label of `depth` min-hash
values for each of `trees` prefix tries. Texts that agree on the first `shallow` values of a label lie under one node of
that trie; the tries are kept sorted by prefix, so that a node's texts are neighbours. Matched prefixes start at full
depth and are shortened no further than the recall asks: a text that is alone, or in small company, under its shallow
nodes is looked up there, which costs little and brings most of the recall. Where a shallow node is crowded (over `block`
texts), its texts descend together to the deepest level at which each still meets a text at the threshold in some trie
with the target probability, given how many of its own tries are crowded. So the depth follows the data: unusual texts
have short prefixes everywhere, and boilerplate and large groups of copies long ones.

Each node's texts verify their pairs exactly, on the word n-grams themselves (numbered without collision inside a node).
A pair is looked at only in the first trie where it meets, so that every pair is verified once and nothing needs to be
made distinct.

Pairs are never rows. A node sends one row per text, and each text's count of links and its root in the node's own
spanning forest come out. Nodes above `block` texts are cut in blocks; each block verifies its own pairs and goes on as
one packed row (a word list and numbers), and pairs of blocks meet in tasks of their own: texts are sent once a node, and
no task holds a node of unbounded size. Only texts that have a pair to verify in a small node are sent there. Joins on
nodes are salted, since one node may hold a third of all texts. Classes are the connected components of the roots, found
by alternating star contraction with a checkpoint per round.

Null texts and texts without words have no shingles: each is a class of its own without links. Texts of fewer words than
a shingle have one shingle of all their words. Class ids are the least document id of the class; null ids are never least.
Repeated rows are copies of one another; an empty table gives an empty result; columns other than the two named aren't
read, whatever their names.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import WordHashes, cut, map_arrow, mixed, rolled, slices, stored, text_function, words_of

#: Parts that the rows of one key are dealt to in joins on nodes and roots.
SALTS = 8


@dataclass(frozen=True)
class Forest:
    shingle: int = 5
    threshold: float = 0.8
    trees: int = 20
    shallow: int = 4
    depth: int = 8
    recall: float = 0.999
    block: int = 256

    def level(self, crowded: int) -> int:
        """The deepest prefix for `crowded` tries, the others being at `shallow`, that keeps the target recall at the threshold."""
        for d in range(self.depth, self.shallow, -1):
            missed = (1 - self.threshold**self.shallow) ** (self.trees - crowded) * (1 - self.threshold**d) ** crowded
            if 1 - missed >= self.recall:
                return d
        return self.shallow


class Signer:
    """Labels of a shingle set: for each trie a key of the first `shallow` min-hash values, and 16 bits of each further one."""

    def __init__(self, forest: Forest):
        self.trees, self.depth, self.shallow = forest.trees, forest.depth, forest.shallow
        n = np.arange(1, self.trees * self.depth + 1, dtype=np.uint64)
        self.times, self.plus = mixed(n * np.uint64(0x51ED27)) | np.uint64(1), mixed(n + np.uint64(0xA5A5))
        self.tree = mixed(np.arange(1, self.trees + 1, dtype=np.uint64) * np.uint64(0xC0FFEE))

    def label(self, shingles: np.ndarray) -> tuple[np.ndarray, bytes]:
        low = np.full(len(self.times), np.iinfo(np.uint64).max, np.uint64)
        for at in range(0, len(shingles), 256):
            part = np.multiply.outer(shingles[at : at + 256], self.times)
            part += self.plus
            np.minimum(low, part.min(axis=0), out=low)
        low = low.reshape(self.depth, self.trees)
        key = self.tree.copy()
        for d in range(self.shallow):
            key = mixed(key + low[d])
        return key.view(np.int64), mixed(low[self.shallow :].T).astype("<u2").tobytes()


def shingles(hashes: np.ndarray, size: int) -> np.ndarray:
    """The sorted distinct hashes of all runs of `size` words; of all words if there are fewer."""
    if not len(hashes):
        return hashes
    return np.unique(rolled(hashes, min(size, len(hashes))))


def digest(words: list[bytes]) -> bytes:
    return xxhash.xxh3_128_digest(b" ".join(words))


def signed(docs: DataFrame, forest: Forest, id_col: str, text_col: str) -> DataFrame:
    """(id, h, keys, tails): the class of copies and the labels of each row; null where there are no words."""

    def sign(batches: Iterator[pa.RecordBatch]):
        signer, hashes = Signer(forest), WordHashes()
        for batch in slices(batches, 256):
            h, keys, tails = [], [], []
            for text in batch.column(1).to_pylist():
                words = words_of(text or "")
                key, tail = signer.label(shingles(hashes.array(words), forest.shingle)) if words else (None, None)
                h.append(digest(words) if words else None)
                keys.append(key)
                tails.append(tail)
            yield {"id": batch.column(0), "h": h, "keys": keys, "tails": tails}

    kind = docs.schema[id_col].dataType.simpleString()
    return map_arrow(docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")), sign, f"id {kind}, h binary, keys array<bigint>, tails binary")


def groups(batches: Iterator[pa.RecordBatch], by: list[str]) -> Iterator[pa.Table]:
    """Runs of rows with equal `by` columns, of rows that come sorted by these."""
    held: list[pa.Table] = []
    for batch in batches:
        table = pa.Table.from_batches([batch])
        if not table.num_rows:
            continue
        if held:
            last = held[-1].slice(held[-1].num_rows - 1)
            if any(last[c][0] != table[c][0] for c in by):
                yield pa.concat_tables(held)
                held = []
        differ = np.zeros(table.num_rows - 1, bool)
        for c in by:
            col = table[c].combine_chunks()
            differ |= pc.not_equal(col.slice(1), col.slice(0, len(col) - 1)).to_numpy(zero_copy_only=False)
        cuts = [0, *(np.flatnonzero(differ) + 1).tolist(), table.num_rows]
        for a, b in zip(cuts, cuts[1:]):
            held.append(table.slice(a, b - a))
            if b < table.num_rows:
                yield pa.concat_tables(held)
                held = []
    if held:
        yield pa.concat_tables(held)


def own_pairs(nodes: np.ndarray, node: int, part: np.ndarray) -> np.ndarray:
    """Which pairs of a node's rows (by their nodes in all tries) meet in no earlier trie: those within the one part, or across two."""
    tree = int(np.flatnonzero(nodes[0] == node)[0])
    mine = part[:, None] != part[None, :] if (part != part[0]).any() else ~np.eye(len(part), dtype=bool)
    for t in range(tree):
        mine &= nodes[:, t][:, None] != nodes[:, t][None, :]
    return mine


def matrix(table: pa.Table, column: str) -> np.ndarray:
    """A column of lists of equal length as a matrix."""
    return pc.list_flatten(table[column]).to_numpy().reshape(table.num_rows, -1)


def numbered(texts: Iterable[list[bytes]]) -> tuple[np.ndarray, np.ndarray, dict[bytes, int]]:
    """All texts' words as numbers, one text behind the other; the texts' lengths; and the numbers by word.

    Each text's words are let go before the next one's are made, so that a node of long texts takes four bytes a word.
    """
    known: dict[bytes, int] = defaultdict(lambda: len(known))
    ids = [np.fromiter(map(known.__getitem__, words), np.int32, len(words)) for words in texts]
    lengths = np.array([len(t) for t in ids], np.int64)
    return np.concatenate([*ids, np.zeros(0, np.int32)]).astype(np.int64), lengths, dict(known)


def shingle_sets(ids: np.ndarray, lengths: np.ndarray, size: int) -> list[np.ndarray]:
    """Each text's set of shingles, as numbers that two shingles share only if they have the same words.

    A run of words is numbered by the rank of its two overlapping halves among all such pairs, so no hash is involved.
    """
    if not len(ids):
        return [ids for _ in lengths]
    gram, have = ids, 1
    while have < size and len(gram) > 1:
        step = min(have, size - have, len(gram) - 1)
        gram = np.unique(gram[:-step] * np.int64(int(gram.max()) + 1) + gram[step:], return_inverse=True)[1]
        have += step
    starts = np.cumsum(lengths) - lengths
    short, out = {}, []
    for start, n in zip(starts.tolist(), lengths.tolist()):
        if n >= size:
            out.append(np.unique(gram[start : start + n - size + 1]))
        else:  # one shingle of all words, which no run of `size` words equals
            out.append(np.array([-1 - short.setdefault(tuple(ids[start : start + n].tolist()), len(short))][: min(n, 1)], np.int64))
    return out


class Block:
    """Texts of one part of a large node as a row: their words' list and numbers, digests, least ids' rows and nodes."""

    @staticmethod
    def packed(ids: np.ndarray, lengths: np.ndarray, known: dict[bytes, int], table: pa.Table) -> bytes:
        sink = pa.BufferOutputStream()
        with pa.ipc.new_stream(sink, table.schema) as writer:
            writer.write_table(table)
        pieces = [b"\n".join(known), ids.astype("<u4").tobytes(), lengths.astype("<i8").tobytes(), sink.getvalue().to_pybytes()]
        sizes = np.array([len(x) for x in pieces], "<i8").tobytes()
        return zstandard.ZstdCompressor(level=3).compress(sizes + b"".join(pieces))

    def __init__(self, data: bytes):
        raw = zstandard.ZstdDecompressor().decompress(data)
        ends = 32 + np.cumsum(np.frombuffer(raw[:32], "<i8"))
        words, ids, lengths, rows = (raw[a:b] for a, b in zip([32, *ends], ends))
        self.words = words.split(b"\n")
        self.ids, self.lengths = np.frombuffer(ids, "<u4").astype(np.int64), np.frombuffer(lengths, "<i8")
        self.table = pa.ipc.open_stream(rows).read_all()

    def renumbered(self, known: dict[bytes, int]) -> np.ndarray:
        return np.array([known.setdefault(w, len(known)) for w in self.words], np.int64)[self.ids]


def shared_counts(sets: list[np.ndarray]) -> np.ndarray:
    """Sizes of all pairwise intersections."""
    if len(sets) == 2:
        both = len(sets[0]) + len(sets[1]) - len(np.union1d(*sets))
        return np.array([[len(sets[0]), both], [both, len(sets[1])]])
    owner = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    values, at, count = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    several = count >= 2
    column = np.cumsum(several) - 1
    keep = several[at]
    owner, column = owner[keep], column[at[keep]]
    order = np.argsort(column, kind="stable")
    owner, column = owner[order], column[order]
    out = np.zeros((len(sets), len(sets)), np.float32)
    width = 4096
    for lo in range(0, int(several.sum()), width):
        a, b = np.searchsorted(column, [lo, lo + width])
        m = np.zeros((len(sets), width), np.float32)
        m[owner[a:b], column[a:b] - lo] = 1
        out += m @ m.T
    return np.rint(out).astype(np.int64)


def linked(sets: list[np.ndarray], mine: np.ndarray, threshold: float) -> np.ndarray:
    both = shared_counts(sets)
    size = np.array([len(s) for s in sets])
    union = size[:, None] + size[None, :] - both
    return mine & (both >= threshold * union - 1e-9)


def roots(links: np.ndarray) -> np.ndarray:
    """Each row's least row within its connected part."""
    n = len(links)
    label = np.arange(n)
    far = np.iinfo(np.int64).max
    while True:
        low = np.minimum(label, np.where(links, label[None, :], far).min(axis=1, initial=far))
        low = low[low]
        if (low == label).all():
            return label
        label = low


def salted_join(many: DataFrame, few: DataFrame, key: str, by: Column, how: str = "inner") -> DataFrame:
    """many.join(few, key), where a key that has any share of `many` is dealt by a hash of `by`, and each row of `few`, one per
    key, is sent to all parts. `few` grows with the data, so it is merged, never broadcast."""
    salt = many.withColumn("_salt", F.pmod(F.xxhash64(by), F.lit(SALTS)))
    return salt.join(few.withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(SALTS - 1).cast("bigint")))).hint("merge"), [key, "_salt"], how).drop("_salt")


def components(edges: DataFrame, rounds: int = 40) -> DataFrame:
    """(node, root) of the connected components of edges (u, v): alternating large and small stars, a checkpoint each round."""

    def star(e: DataFrame, small: bool) -> DataFrame:
        both = e.select(F.col("u").alias("x"), F.col("v").alias("y")).unionAll(e.select(F.col("v").alias("x"), F.col("u").alias("y")))
        near = both.where("y < x") if small else both
        low = near.groupBy("x").agg(F.min("y").alias("m")).withColumn("m", F.least("m", "x"))
        moved = salted_join(near, low, "x", F.col("y")).where("y < x" if small else "y > x")
        out = moved.select(F.col("y").alias("u"), F.col("m").alias("v"))
        if small:
            out = out.unionAll(low.select(F.col("x").alias("u"), F.col("m").alias("v")))
        return out.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()

    sign = lambda e: tuple(e.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v"))).first())
    edges = cut(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct())
    was = sign(edges)
    for _ in range(rounds):
        edges = cut(star(star(edges, small=False), small=True))
        now = sign(edges)
        if now == was:
            break
        was = now
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    return edges.select(F.col("u").alias("node"), F.col("v").alias("root"))


def located(texts: DataFrame, forest: Forest) -> DataFrame:
    """(h, rep, nodes) of the texts that meet another one: their node in each trie, of a depth that follows the data."""
    keyed = texts.select("h", F.posexplode("keys").alias("tree", "key"))
    sizes = keyed.groupBy("key").agg(F.count("*").alias("n")).where("n > 1")
    met = stored(salted_join(keyed, sizes, "key", F.col("h")), "shallow-nodes")
    # Crowded nodes: the deepest level that every text of theirs allows.
    crowded = met.where(F.col("n") > forest.block)
    levels = F.array(*[F.lit(forest.level(g)) for g in range(forest.trees + 1)])
    allowed = crowded.groupBy("h").agg(F.element_at(levels, F.count("*").cast("int") + 1).alias("level"))
    taken = crowded.join(allowed, "h").groupBy("key").agg(F.min("level").alias("level"))
    width = 2 * (forest.depth - forest.shallow)
    deep = salted_join(crowded.select("h", "tree", "key"), taken, "key", F.col("h")).join(texts.select("h", "tails"), "h")
    tail = F.substring("tails", F.col("tree") * width + 1, 2 * (F.col("level") - forest.shallow))
    below = deep.select("h", F.struct("tree", F.when(F.col("level") > forest.shallow, F.xxhash64("key", tail)).otherwise(F.col("key")).alias("node")).alias("at"))
    below = below.groupBy("h").agg(F.map_from_entries(F.collect_list("at")).alias("below"))  # at most one entry a trie
    mine = texts.select("h", "rep", "keys").join(met.select("h").distinct(), "h").join(below, "h", "left")
    return mine.select("h", "rep", F.transform("keys", lambda k, t: F.coalesce(F.col("below")[t], k)).alias("nodes"))


def ngram_jaccard_join(docs: DataFrame, *, forest: Forest = Forest(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, class_id, n_links (other texts at or above the threshold), n_copies (rows with its words)."""
    return _joined(docs, forest, id_col, text_col, heads=False)


def marked_rows(docs: DataFrame, *, forest: Forest = Forest(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, h (its words' digest, null without words), kept: is it the one (id, h) that stands for its class?"""
    return _joined(docs, forest, id_col, text_col, heads=True)


def digest_column():
    """A column function text -> struct(h): the digest of its words, null without words."""

    def make():
        return lambda texts: [{"h": digest(w) if (w := words_of(t or "")) else None} for t in texts]

    return text_function(make, "h binary")


def _joined(docs: DataFrame, forest: Forest, id_col: str, text_col: str, heads: bool) -> DataFrame:
    kind = docs.schema[id_col].dataType.simpleString()
    rows = stored(signed(docs, forest, id_col, text_col), "signatures")
    texts = stored(rows.where("h IS NOT NULL").groupBy("h").agg(F.min("id").alias("rep"), F.count("*").alias("copies"), F.first("keys").alias("keys"), F.first("tails").alias("tails")), "texts")

    # One row for each text and node of its that others share; large nodes are cut in parts.
    places = stored(located(texts, forest), "nodes").select("h", "rep", "nodes", F.explode("nodes").alias("node"))
    sizes = places.groupBy("node").agg(F.count("*").alias("n")).where("n > 1").select("node", F.ceil(F.col("n") / forest.block).cast("int").alias("parts"))
    member = salted_join(places, sizes, "node", F.col("h")).select("node", F.pmod(F.xxhash64("h"), "parts").cast("int").alias("part"), "parts", "h", "rep", "nodes")
    by = ["node", "part"]
    columns = f"node bigint, part int, parts int, h binary, rep {kind}, nodes array<bigint>"
    in_groups = lambda df, by: df.repartition(*by).sortWithinPartitions(*by, "h")

    def needed(batches):
        """Members of small nodes that have a pair of their own there, and all those of large ones."""
        for table in groups(batches, by):
            if table["parts"][0].as_py() == 1:
                if table.num_rows < 2:
                    continue
                mine = own_pairs(matrix(table, "nodes"), table["node"][0].as_py(), table["part"].to_numpy())
                table = table.filter(pa.array(mine.any(axis=1)))
            if table.num_rows:
                yield {c: table[c].combine_chunks() for c in table.column_names}

    candidates = map_arrow(in_groups(member, by), needed, columns)
    whole = docs.select(F.col(id_col).alias("rep"), F.col(text_col).alias("text")).where("text IS NOT NULL")
    worded = candidates.alias("c").join(whole.alias("d"), F.expr("c.rep <=> d.rep")).select("c.*", "d.text")
    result = f"h binary, rep {kind}, links bigint, top binary"

    def found(table: pa.Table, sets: list[np.ndarray], part: np.ndarray) -> dict:
        """Counts of links and roots of the texts that have any, as columns."""
        links = linked(sets, own_pairs(matrix(table, "nodes"), table["node"][0].as_py(), part), forest.threshold)
        count = links.sum(axis=1)
        some = np.flatnonzero(count)
        top = roots(links)[some]
        return {"h": table["h"].take(pa.array(some)).combine_chunks(), "rep": table["rep"].take(pa.array(some)).combine_chunks(), "links": count[some], "top": table["h"].take(pa.array(top)).combine_chunks()}

    def verify(batches):
        for table in groups(batches, by):
            keep, seen, column = [], set(), table["text"]

            def texts(table=table, keep=keep, seen=seen, column=column):
                for k, h in enumerate(table["h"].to_pylist()):
                    if h not in seen and digest(words := words_of(column[k].as_py())) == h:
                        seen.add(h)
                        keep.append(k)
                        yield words

            ids, lengths, known = numbered(texts())
            table = table.drop_columns(["text"]).take(pa.array(keep, pa.int64()))
            if not keep:
                continue
            node, part, parts = (table[c][0].as_py() for c in ("node", "part", "parts"))
            if len(keep) > 1:
                got = found(table, shingle_sets(ids, lengths, forest.shingle), table["part"].to_numpy())
                n = len(got["links"])
                yield got | {c: pa.nulls(n, t) for c, t in (("node", pa.int64()), ("part", pa.int32()), ("parts", pa.int32()), ("block", pa.binary()))}
            if parts > 1:
                nothing = {"h": [None], "rep": pa.nulls(1, table.schema.field("rep").type), "links": [None], "top": [None]}
                yield nothing | {"node": [node], "part": [part], "parts": [parts], "block": [Block.packed(ids, lengths, known, table)]}

    def across(batches):
        """Pairs between two parts of a node."""
        for table in groups(batches, ["node", "i", "j"]):
            if table.num_rows < 2:
                continue
            known: dict[bytes, int] = {}
            blocks = [Block(x) for x in table["block"].to_pylist()]
            ids = np.concatenate([b.renumbered(known) for b in blocks])
            both = pa.concat_tables([b.table for b in blocks])
            yield found(both, shingle_sets(ids, np.concatenate([b.lengths for b in blocks]), forest.shingle), both["part"].to_numpy())

    first = stored(map_arrow(in_groups(worded, by), verify, f"{result}, node bigint, part int, parts int, block binary"), "links")
    blocks = first.where("block IS NOT NULL").select("node", "part", "block", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("other")).where("other <> part")
    blocks = blocks.select("node", F.least("part", "other").alias("i"), F.greatest("part", "other").alias("j"), "part", "block")
    second = map_arrow(blocks.repartition("node", "i", "j").sortWithinPartitions("node", "i", "j", "part"), across, result)
    verified = stored(first.where("h IS NOT NULL").select("h", "rep", "links", "top").unionAll(second), "all-links")
    edges = verified.select(F.col("h").alias("u"), F.col("top").alias("v"))
    label = components(edges)
    nodes = verified.groupBy("h").agg(F.min("rep").alias("rep"), F.sum("links").alias("n_links"))
    nodes = nodes.join(label, nodes["h"] == label["node"], "left").select("h", "rep", "n_links", F.coalesce("root", "h").alias("root"))
    head = [F.min_by("h", F.struct(F.col("rep").isNull(), "rep", "h")).alias("head")] if heads else []
    least = nodes.groupBy("root").agg(F.min("rep").alias("class_id"), *head)
    classes = salted_join(nodes, least, "root", F.col("h")).select("h", "class_id", "n_links", *["head"] * heads)
    copied = texts.where("copies > 1").select("h", "rep", "copies")
    about = copied.join(classes, "h", "full_outer").select("h", F.coalesce("class_id", "rep").alias("class_id"), "n_links", "copies", *["head"] * heads)
    out = rows.select("id", "h").join(about, "h", "left")
    if heads:
        stands = F.col("id").eqNullSafe(F.coalesce("class_id", "id")) & (F.coalesce("head", "h") == F.col("h"))
        return out.select(F.col("id").alias(id_col), "h", (F.col("h").isNull() | stands).alias("kept"))
    zero = lambda c, v: F.coalesce(F.col(c), F.lit(v)).cast("bigint").alias(c)
    return out.select(F.col("id").alias(id_col), F.coalesce("class_id", "id").alias("class_id"), zero("n_links", 0), F.coalesce("copies", F.lit(1)).cast("bigint").alias("n_copies"))


def oracle_sql(forest: Forest = Forest()) -> str:
    """The same result in DuckDB SQL by an exact join on shingles: for small tables, as it makes all pairs that share one."""
    k = forest.shingle
    return f"""
WITH RECURSIVE d AS (SELECT row_number() OVER () AS r, doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS w FROM documents),
k AS (SELECT r, doc_id, w, array_to_string(w, ' ') AS k FROM d),
t AS (SELECT k, any_value(w) AS w, count(*) AS copies, min(doc_id) AS rep FROM k WHERE len(w) > 0 GROUP BY 1), n AS (SELECT *, row_number() OVER (ORDER BY k) AS x FROM t),
s AS (SELECT x, unnest(list_distinct(CASE WHEN len(w) < {k} THEN [k] ELSE list_transform(range(1, len(w) - {k - 2}), lambda i: array_to_string(w[i : i + {k - 1}], ' ')) END)) AS s FROM n),
z AS (SELECT x, count(*) AS z FROM s GROUP BY 1),
b AS (SELECT p.x AS a, q.x AS b, count(*) AS m FROM s p JOIN s q ON p.s = q.s AND p.x < q.x GROUP BY 1, 2),
e AS (SELECT a, b FROM b JOIN z za ON za.x = a JOIN z zb ON zb.x = b WHERE m >= {forest.threshold} * (za.z + zb.z - m) - 1e-9),
u AS (SELECT a, b FROM e UNION ALL SELECT b, a FROM e),
g(x, root) AS (SELECT x, x FROM n UNION SELECT u.b, g.root FROM g JOIN u ON u.a = g.x),
c AS (SELECT x, min(root) AS root FROM g GROUP BY 1), m AS (SELECT root, min(rep) AS class_id FROM c JOIN n USING (x) GROUP BY 1),
l AS (SELECT a AS x, count(*) AS links FROM u GROUP BY 1)
SELECT doc_id, CAST(coalesce(class_id, doc_id) AS BIGINT) AS class_id, CAST(coalesce(links, 0) AS BIGINT) AS n_links, CAST(coalesce(copies, 1) AS BIGINT) AS n_copies
FROM k LEFT JOIN n USING (k) LEFT JOIN c USING (x) LEFT JOIN m USING (root) LEFT JOIN l USING (x)"""
