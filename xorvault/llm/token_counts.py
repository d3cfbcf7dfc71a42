"""Token counts under a unigram model, by dynamic programming over a trie of pre-tokens.

A unigram model gives each piece a log-probability; a pre-token's tokens are those of its most probable cut into
pieces. Distinct pre-tokens are put in a trie: a node stands for a prefix and keeps the prefix's best forward score and
the token count of that cut, so that prefixes which pre-tokens share are worked out once. The counts at terminal nodes
are what documents sum up. Ties go to fewer tokens.

Piece probabilities follow the ranks of a public byte-level vocabulary by a Zipf-Mandelbrot law with a stated offset;
nothing is trained. All 256 bytes are pieces, so every text has a cut.

Pre-tokens share prefixes only near their start, so nodes are kept for the first SHARED_BYTES bytes; the rest of a longer
word is walked with the scores of a bounded window, exactly, and neither stored nor remembered.

Null and empty texts have no tokens (0 and log_score 0); repeated rows give repeated results; an empty table gives an
empty one; columns other than the two named aren't read, whatever their names; ties go to the cut of fewer tokens.
"""

from __future__ import annotations

import base64
import math
from functools import lru_cache

import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import text_function
from .pair_index_bpe import PRETOKEN

#: Trie nodes, and pre-tokens with their results, that a Python worker remembers.
NODES_REMEMBERED = 600_000
WORDS_REMEMBERED = 500_000
ZIPF_OFFSET = 2.7
#: Bytes of a pre-token that the trie has nodes for, and scores that a walk beyond them holds before it drops the oldest.
SHARED_BYTES = 64
PATH_HELD = 4096


def default_ranks() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken")


def piece_scores(path: str, offset: float = ZIPF_OFFSET) -> dict[bytes, float]:
    """Natural log-probabilities of the pieces of a rank file (base64 piece, rank)."""
    with open(path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}
    total = math.log(sum(1 / (r + offset) for r in ranks.values()))
    return {piece: -math.log(r + offset) - total for piece, r in ranks.items()}


class PretokenTrie:
    def __init__(self, scores: dict[bytes, float]):
        self.scores = scores
        lengths: dict[bytes, set[int]] = {}
        for piece in scores:
            if len(piece) > 1:
                lengths.setdefault(piece[-2:], set()).add(len(piece))
        self.lengths = {end: tuple(sorted(x)) for end, x in lengths.items()}
        self.longest = max(map(len, scores))
        self.find = regex.compile(PRETOKEN).findall
        self.terminal: dict[str, complex] = {}
        self.reset()

    def reset(self) -> None:
        """An empty trie: `nodes` maps 256 * parent + byte to a node, `forward` has each node's score; node 0 is the root."""
        # A result is one complex number, log-probability + tokens * 1j, so that one sum adds up both.
        self.nodes: dict[int, int] = {}
        self.forward: list[complex] = [0j]

    def insert(self, word: str) -> complex:
        """Put word in the trie: only the nodes beyond its longest known prefix are worked out.

        Beyond SHARED_BYTES nothing is stored: the walk goes on with the scores of the last prefixes, as many as the
        longest piece has bytes, so that a word of any length takes bounded memory.
        """
        if len(self.forward) > NODES_REMEMBERED:
            self.reset()
        data, nodes, forward, scores, lengths = word.encode("utf-8"), self.nodes, self.forward, self.scores, self.lengths
        n, node, path = len(data), 0, [0j]
        shared = min(n, SHARED_BYTES)
        have = 0
        while have < shared and (child := nodes.get(node << 8 | data[have])) is not None:
            node = child
            have += 1
            path.append(forward[node])
        gone = 0  # scores that have left the path's front
        for end in range(have + 1, n + 1):
            best = path[-1] + complex(scores[data[end - 1 : end]], 1)
            top, count = best.real, best.imag
            for size in lengths.get(data[end - 2 : end], ()) if end > 1 else ():
                if size > end:
                    break
                p = scores.get(data[end - size : end])
                if p is not None:
                    z = path[end - size - gone]
                    s = z.real + p
                    if s > top or s == top and z.imag + 1 < count:
                        top, count = s, z.imag + 1
            path.append(complex(top, count))
            if end <= shared:
                forward.append(path[-1])
                nodes[node << 8 | data[end - 1]] = node = len(forward) - 1
            elif len(path) > PATH_HELD:
                gone += len(path) - self.longest
                del path[: -self.longest]
        return path[-1]

    def count(self, texts: list[str]) -> list[dict]:
        split = [self.find(t) for t in texts]
        terminal, long = self.terminal, []
        for tokens in split:
            for word in set(tokens):
                if word not in terminal:
                    terminal[word] = self.insert(word)
                    if len(word) > SHARED_BYTES:
                        long.append(word)
        get, out = terminal.__getitem__, []
        for text, tokens in zip(texts, split):
            total = sum(map(get, tokens), 0j)
            out.append({"n_pretokens": len(tokens), "n_tokens": round(total.imag), "n_bytes": len(text.encode("utf-8")), "log_score": total.real})
        for word in long:  # they are rare and large
            terminal.pop(word, None)
        if len(terminal) > WORDS_REMEMBERED:  # words in use stay
            self.terminal = {t: terminal[t] for tokens in split for t in tokens if t in terminal}
        return out


@lru_cache(maxsize=2)
def loaded(path: str) -> PretokenTrie:
    return PretokenTrie(piece_scores(path))


def count_tokens(docs: DataFrame, *, path: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, n_pretokens, n_tokens, n_bytes and the log-probability of the best cut."""
    at = path or default_ranks()
    column = text_function(lambda: loaded(at).count, "n_pretokens bigint, n_tokens bigint, n_bytes bigint, log_score double")
    return docs.select(F.col(id_col), column(F.col(text_col)).alias("_r")).select(id_col, "_r.*")
