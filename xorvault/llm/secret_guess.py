"""Secret scans: fixed patterns, and a guess-cost estimate for values that stand in a credential context.

The estimate is the least number of guesses (as a power of ten) over all ways to cut a value into dictionary words,
dates, repeats, keyboard or alphabet walks and brute-force spans. One dynamic program over the value's positions finds
it: each position holds the cheapest cut that ends there, once with an open brute-force span and once without. Words are
read off a trie; walks, and repeats of each period, come from one pass over the value each, so that the work is linear
in the value's length. The words are a short fixed list and the whole words of a public vocabulary file, by rank. Values
that cost more than a limit are reported as kind `guess`, but for those that only name a variable or a path of
identifiers (`process.env.API_KEY`): they say where a secret is kept.

Null and empty texts have no spans. Offsets are in code points, ends exclusive. Spans that start together stand in the
order of KINDS, then of their ends. Repeated rows give repeated results, an empty table an empty one; columns other than
the two named aren't read, whatever their names.
"""

from __future__ import annotations

import hashlib
import json
import math
import re
import string
from array import array
from functools import lru_cache
from itertools import accumulate
from operator import ne

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import text_function

# The base patterns, and the least length of what counts (assign: of its second group).
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{16,}")
KINDS = ("assign", "access", "hex", "guess")

CONTEXT = re.compile(r"""(?:pass(?:word|wd|phrase|code)?|pwd|secret|token|(?:api|access|private|account)[_-]?key|credentials?|auth)["']?[\x20\t]{0,8}(?:=>|:=|[:=])[\x20\t]{0,8}["']?([^\s"'<>,;]{6,})""", re.I | re.A)

# Words that people put in passwords and placeholders, most usual first. Those of a vocabulary file follow.
WORDS = "password pass secret admin login welcome test user guest root changeme default example sample letmein master hello love dragon monkey football baseball sunshine princess shadow qwerty token key api demo temp dummy placeholder your here none null true false value string enter insert replace this with the my new old dev prod local host server system data base account access code money summer winter spring autumn monday friday blue red green black white star home work phone".split()
CAPITALS = str.maketrans(string.ascii_uppercase, string.ascii_lowercase)
LEET = str.maketrans("013457@$!", "oleastasi")
ROWS = ("qwertyuiop", "asdfghjkl", "zxcvbnm", "1234567890", "abcdefghijklmnopqrstuvwxyz", "0123456789")
DATE = re.compile(r"(?:19|20)\d\d(?:([-/._]?)(?:0[1-9]|1[0-2])\1(?:0[1-9]|[12]\d|3[01]))?|(?:0[1-9]|[12]\d|3[01])([-/._]?)(?:0[1-9]|1[0-2])\2(?:19|20)\d\d")
PERIODS = (1, 2, 3, 4)

NEXT = {(a, b) for row in ROWS for a, b in [*zip(row, row[1:]), *zip(row[1:], row)]}
#: Each segment beyond the first multiplies the guesses by this power of ten, as an attacker must also guess the cut.
CUT = 0.6

#: A value that names where a secret is kept: a variable, or a path of identifiers, that may be called or indexed.
REFERENCE = re.compile(r"(?:[$@%][({]{0,2}|\{\{)[A-Za-z_][\w.]*|([A-Za-z_]\w*(?:(?:\.|::|->|\?\.)[A-Za-z_]\w*)+)(?:[()\[\]].*)?\Z|([A-Za-z_]\w*)(?:\(|\[).*", re.A | re.S)


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


class Guesser:
    """Guess costs by a ranked word list: the fixed words, then a vocabulary file's whole words by their ids."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            vocabulary = json.load(f)["model"]["vocab"]
        whole = re.compile("\u0120([A-Za-z]{3,})")
        found = (m[1].translate(CAPITALS) for piece in sorted(vocabulary, key=vocabulary.get) if (m := whole.fullmatch(piece)))
        self.rank = {w: k + 1 for k, w in enumerate(dict.fromkeys([*WORDS, *found]))}
        self.trie: dict = {}
        for w, k in self.rank.items():
            node = self.trie
            for c in w:
                node = node.setdefault(c, {})
            node[""] = k

    def words_at(self, text: str, i: int) -> list[tuple[int, int]]:
        """(end, rank) of the words that start at i."""
        out, node, j, n = [], self.trie, i, len(text)
        while j < n and (node := node.get(text[j])) is not None:
            j += 1
            if "" in node:
                out.append((j, node[""]))
        return out

    def log10_guesses(self, value: str) -> float:
        """The least log10 of guesses over all segmentations of value."""
        n = len(value)
        if not n:
            return 0.0
        low = value.translate(CAPITALS)
        plain = low.translate(LEET)
        card = array("d", map(_cardinality, value))
        before = array("d", accumulate(card, initial=0.0))
        walks, repeats = walks_of(low), [repeats_of(value, p) for p in PERIODS]
        changed = array("l", accumulate(map(ne, value, low), initial=0))
        leet = array("l", accumulate(map(ne, low, plain), initial=0))
        free, brute = array("d", [math.inf]) * (n + 1), array("d", [math.inf]) * (n + 1)
        free[0] = -CUT
        for i in range(n):
            start = min(free[i], brute[i]) + CUT
            brute[i + 1] = min(brute[i + 1], min(brute[i], start) + card[i])
            for j, rank in self.words_at(plain, i):
                odd = leet[j] > leet[i]  # letters written as digits or signs
                cost = start + math.log10(rank) + 0.3 * (changed[j] > changed[i]) + 0.6 * odd
                free[j] = min(free[j], cost)
            if value[i].isdigit() and (m := DATE.match(value, i)):
                j = m.end()
                free[j] = min(free[j], start + math.log10(120 if j - i == 4 else 120 * 365) + 0.6 * bool(m[1] or m[2]))
            if walks[i] - i >= 3:
                for j in (walks[i], i + 3):
                    free[j] = min(free[j], start + math.log10(47 * (j - i)))
            for size, run in zip(PERIODS, repeats):
                times = run[i] // size + 1
                if times >= 2 and times * size >= 3:
                    j = i + size * times
                    free[j] = min(free[j], start + before[i + size] - before[i] + math.log10(times))
        return min(free[n], brute[n])

    def is_reference(self, value: str, least: float) -> bool:
        """Does value name a place that holds a secret? Each identifier must be cheap to guess, as random ones aren't."""
        m = REFERENCE.match(value)
        if not m:
            return False
        return all(self.log10_guesses(x) < least for x in re.split(r"\W+|_", m[1] or m[2] or "") if x)

    def spans(self, text: str, least: float) -> list[tuple[str, int, int]]:
        return [("guess", *m.span(1)) for m in CONTEXT.finditer(text) if self.log10_guesses(m[1]) >= least and not self.is_reference(m[1], least)]


def walks_of(low: str) -> array:
    """For each place, where the longest keyboard or alphabet walk from there ends."""
    walks, end = array("l", [0]) * len(low), len(low)
    for i in range(len(low) - 1, -1, -1):
        end = end if i + 1 < len(low) and (low[i], low[i + 1]) in NEXT else i + 1
        walks[i] = end
    return walks


def repeats_of(value: str, period: int) -> array:
    """For each place, how many characters from there on equal the one a period later."""
    run = array("l", [0]) * (len(value) + 1)
    for i in range(len(value) - period - 1, -1, -1):
        if value[i] == value[i + period]:
            run[i] = run[i + 1] + 1
    return run


def _cardinality(c: str) -> float:
    return math.log10(10 if c.isdigit() or c in "-_." else 26 if c.isalpha() and c.isascii() else 33 if c.isascii() else 100)


@lru_cache(maxsize=2)
def loaded(path: str) -> Guesser:
    return Guesser(path)


def base_spans(text: str) -> list[tuple[str, int, int]]:
    found = [("assign", *m.span()) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 12]
    found += [("access", *m.span()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 18]
    found += [("hex", *m.span()) for m in HEX.finditer(text)]
    return found


def joined(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in sorted(spans, key=lambda s: (s[1], KINDS.index(s[0]), s[2])))


def redacted(text: str, spans: list[tuple[str, int, int]], mask: str = "<secret>") -> str:
    """text with the union of the spans masked."""
    out, at, until = [], 0, -1
    for _, a, b in sorted(spans, key=lambda s: (s[1], s[2])):
        if a > until:
            out += [text[at:a], mask]
            until = at = b
        elif b > until:
            until = at = b
    return "".join([*out, text[at:]])


def secrets_column(least: float = 9.0, redact: bool = False, path: str | None = None):
    """A column function text -> struct of counts, digest and spans, or of the redacted text."""
    at = path or default_vocabulary()

    def make():
        guesser = loaded(at)

        def one(text: str) -> dict:
            base = base_spans(text)
            spans = base + guesser.spans(text, least)
            if redact:
                return {"text": redacted(text, spans) if spans else text, "n_spans": len(spans)}
            count = lambda kind: sum(s[0] == kind for s in spans)
            return {"n_assign": count("assign"), "n_access": count("access"), "n_hex": count("hex"), "base_sha256": hashlib.sha256(joined(base).encode()).hexdigest(), "spans": joined(spans), "n_guess": count("guess")}

        return lambda texts: [one(x) for x in texts]

    return text_function(make, "text string, n_spans bigint" if redact else "n_assign bigint, n_access bigint, n_hex bigint, base_sha256 string, spans string, n_guess bigint")


def scan_secrets(docs: DataFrame, *, least_log10_guesses: float = 9.0, path: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: counts per kind, digest of the base spans and all spans."""
    return docs.select(F.col(id_col), secrets_column(least_log10_guesses, path=path)(F.col(text_col)).alias("_r")).select(id_col, "_r.*")


