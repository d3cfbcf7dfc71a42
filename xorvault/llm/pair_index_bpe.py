"""Byte-level BPE encoding and decoding with a pair occurrence index.

The distinct pre-tokens of a batch lie one behind the other in arrays of symbols with links to both neighbours. An
index maps each mergeable pair to all its positions in that partition's batch. Active ranks come off a heap in
ascending order; all occurrences of a rank are merged from left to right, and only the lists of the pairs that a merge
creates are touched. Ids of distinct pre-tokens are remembered up to a bound, so that a frequent word is merged once.

Texts: null counts as empty; an empty text has no ids. Whole texts are encoded; nothing depends on row order.
"""

from __future__ import annotations

import hashlib
import heapq
import json
from functools import lru_cache
from itertools import islice

import numpy as np
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import text_function

# Fixed values of byte-level BPE: the published pre-token pattern, and the bytes that stand for themselves in vocabulary files.
PRETOKEN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
SELF_BYTES = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]

#: Distinct pre-tokens whose ids a Python worker remembers in a task, and from one task to the next.
REMEMBERED = 400_000
KEPT = 100_000


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


class PairIndexBpe:
    """Encoder and decoder for a tokenizers JSON file of kind byte-level BPE without normaliser."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        others = [b for b in range(256) if b not in set(SELF_BYTES)]
        self.byte_of = {chr(b): b for b in SELF_BYTES} | {chr(256 + k): b for k, b in enumerate(others)}
        raw = lambda piece: bytes(self.byte_of[c] for c in piece)
        ids = {raw(piece): k for piece, k in model["vocab"].items()}
        self.special = {a["content"]: a["id"] for a in spec.get("added_tokens", [])}
        self.pieces: list[bytes] = [b""] * (1 + max([*ids.values(), *self.special.values()]))
        for piece, k in ids.items():
            self.pieces[k] = piece
        for piece, k in self.special.items():
            self.pieces[k] = piece.encode()
        self.byte_ids = [ids[bytes([b])] for b in range(256)]
        merges = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
        self.rank: dict[tuple[int, int], int] = {}
        self.merged: list[int] = []
        for r, (a, b) in enumerate(merges):
            a, b = raw(a), raw(b)
            self.rank.setdefault((ids[a], ids[b]), r)
            self.merged.append(ids[a + b])
        self.find = regex.compile(PRETOKEN).findall
        self.cut = regex.compile("(" + "|".join(regex.escape(s) for s in sorted(self.special, key=len, reverse=True)) + ")").split if self.special else None
        self.known: dict[str, bytes] = {}

    def merge_all(self, words: list[bytes]) -> list[list[int]]:
        """Ids of each of the distinct byte strings `words`."""
        sym: list[int] = []
        ends: list[int] = []
        byte_ids = self.byte_ids
        for w in words:
            sym.extend([byte_ids[b] for b in w])
            sym.append(-1)
            ends.append(len(sym) - 1)
        n = len(sym)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        rank, merged = self.rank, self.merged
        where: dict[int, list[int]] = {}
        for p, r in enumerate(map(rank.get, zip(sym, sym[1:]))):
            if r is not None:
                if r in where:
                    where[r].append(p)
                else:
                    where[r] = [p]
        active = list(where)
        heapq.heapify(active)
        while active:
            r = heapq.heappop(active)
            spots = where.pop(r, None)
            if spots is None:
                continue
            spots.sort()
            into = merged[r]
            for p in spots:
                a = sym[p]
                if a < 0:
                    continue
                q = after[p]
                if q >= n or rank.get((a, sym[q])) != r:
                    continue
                z = after[q]
                sym[p], sym[q] = into, -2
                after[p] = z
                if z < n:
                    before[z] = p
                    made = rank.get((into, sym[z]))
                    if made is not None:
                        if made in where:
                            where[made].append(p)
                        else:
                            where[made] = [p]
                            heapq.heappush(active, made)
                y = before[p]
                if y >= 0:
                    made = rank.get((sym[y], into))
                    if made is not None:
                        if made in where:
                            where[made].append(y)
                        else:
                            where[made] = [y]
                            heapq.heappush(active, made)
        out, start = [], 0
        for e in ends:
            out.append([s for s in sym[start:e] if s >= 0])
            start = e + 1
        return out

    def encode_batch(self, texts: list[str]) -> list[bytes]:
        """Each text's ids as little-endian unsigned 32-bit integers."""
        known, find = self.known, self.find
        parts: list[list[tuple[bool, list[str] | int]]] = []
        new: set[str] = set()
        for text in texts:
            pieces = [text] if self.cut is None or not any(s in text for s in self.special) else self.cut(text)
            row: list = []
            for k, piece in enumerate(pieces):
                if k % 2:
                    row.append((True, self.special[piece]))
                elif piece:
                    tokens = find(piece)
                    new.update(t for t in set(tokens) if t not in known)
                    row.append((False, tokens))
            parts.append(row)
        fresh = list(new)
        for word, ids in zip(fresh, self.merge_all([w.encode("utf-8") for w in fresh])):
            known[word] = np.array(ids, "<u4").tobytes()
        if len(known) > REMEMBERED:  # words in use stay
            known = self.known = {t: known[t] for row in parts for special, x in row if not special for t in x}
        get = known.__getitem__
        return [b"".join(x.to_bytes(4, "little") if special else b"".join(map(get, x)) for special, x in row) for row in parts]

    def rest(self) -> None:
        """Between tasks, only the pre-tokens that were met first, which are mostly the frequent ones, stay remembered."""
        if len(self.known) > KEPT:
            self.known = dict(islice(self.known.items(), KEPT))

    def decode(self, ids: bytes) -> str:
        return b"".join(map(self.pieces.__getitem__, np.frombuffer(ids, "<u4").tolist())).decode("utf-8", "replace")


@lru_cache(maxsize=2)
def loaded(path: str) -> PairIndexBpe:
    return PairIndexBpe(path)


def bpe_column(path: str, keep_ids: bool = False):
    """A column function text -> struct(n_tokens, ids_sha256, decoded_sha256[, ids array<int>])."""

    def make():
        bpe = loaded(path)

        def work(texts: list[str]) -> list[dict]:
            out = []
            for ids in bpe.encode_batch(texts):
                row = {"n_tokens": len(ids) // 4, "ids_sha256": hashlib.sha256(ids).hexdigest(), "decoded_sha256": hashlib.sha256(bpe.decode(ids).encode("utf-8")).hexdigest()}
                if keep_ids:
                    row["ids"] = np.frombuffer(ids, "<i4").tolist()
                out.append(row)
            return out

        work.rest = bpe.rest
        return work

    return text_function(make, "n_tokens bigint, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * keep_ids)


def encode_documents(docs: DataFrame, *, path: str | None = None, id_col: str = "doc_id", text_col: str = "text", keep_ids: bool = True) -> DataFrame:
    """One row per input row: id, n_tokens, ids_sha256, decoded_sha256 and, with keep_ids, the ids themselves.

    Only the two named columns are read; null texts count as empty (0 ids); repeated rows give repeated results.
    """
    made = docs.select(F.col(id_col), bpe_column(path or default_vocabulary(), keep_ids)(F.col(text_col)).alias("_r"))
    return made.select(id_col, "_r.*")
