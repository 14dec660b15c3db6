r"""Secret scans with character Markov models.

Three base patterns (assignments, access keys, hexadecimal runs) find spans by form. Beside them, second-order Markov models over
characters score every token of 12 and more key-like characters by a log-likelihood ratio: one model of random strings against one of ordinary identifiers and,
for letters in the case of prose (small, capital or capitalised), one of words, whichever explains the token better. A token whose ratio exceeds a limit
``slope * length + offset`` is a span of kind ``markov``, unless a base span holds it whole; nothing else decides.

Models and limits come from labelled samples: strings drawn from the usual key alphabets by a seeded generator (label 1), identifiers composed by
rule (snake, camel, kebab and path case, with counters and dates) from words, and long words: words run together or composed from frequent letter groups
(label 0). The words are those of a public tokenizer's vocabulary file (``words_of``), or a short list without one. They are split in two: one half trains the models, the other
half, with strings of its own, sets the limits, for prose-like tokens and for others: the pair that finds most secrets while at most ``alarms`` of
the ordinary tokens exceed it. Callers can pass samples of their own. The samples do not grow with the corpus, and models are fitted once, on the driver.

Defined cases: null text counts as empty and has no spans; positions are code points, ends exclusive; texts are scanned whole, however long (candidates and base
spans are merged in one pass); rows that repeat an id and rows with a null id give a row each; spans of one start are in the order of the kinds;
an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import math
import random
import re
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from .bpe import read_ranks
from .common import text_of

#: The base patterns; fixed values.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{16,}")  # the runs of 16 and more: shorter ones fail anyway
KINDS = ("assign", "access", "hex", "markov")
CANDIDATE = re.compile(r"[A-Za-z0-9+/_=-]{12,}")
PROSE = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")
ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=-"
#: Words from which ordinary identifiers are composed; fixed values.
WORDS = (
    "user account name value index count total order customer item price region nation date time start end first last "
    "get set find load save parse render update delete create remove insert select filter group merge split table column row key "
    "file path line text string number list map array object class method function module config option default request response "
    "server client session message event handler manager service factory builder reader writer stream buffer cache queue worker thread "
    "internationalization configuration implementation documentation responsibility transformation authentication "
    "information nombre fecha usuario cuenta valor utilisateur compte valeur adresse benutzer konto wert adresse nachricht"
).split()

#: Frequent letter groups of the four languages, from which words are composed; fixed values.
GROUPS = (
    "th he in er an re on at en nd ti es or te of ed is it al ar st to nt ng se ha as ou io le ve co me de hi ri ro ic ne ea ra ce li ch ll be ma si om ur "
    "the and ing ion tion ent for her ter hat tha ere ate his con res ver all ons nce men ith ted ers pro wh sh ly ble ness ment ous ive able ize est "
    "les que des une est ait aux eur eux ais ant oir ique ette elle ois ien ai oi ui an ou "
    "der die und sch ein ich den cht gen ung heit keit lich ver be ge zu ei ie au pf tz bau zeit "
    "os as el la los ado ada ar ar ci ue qu mente dad cion ll rr es do da to ta jo za bo co go gu mi"
).split()


def random_strings(n: int, seed: int = 7, shortest: int = 12) -> list[str]:
    rng = random.Random(seed)
    sets = [ALPHABET[:62], ALPHABET[:64], ALPHABET[:26] + ALPHABET[52:62], ALPHABET[26:62], "0123456789abcdef", ALPHABET[:52]]
    return ["".join(rng.choices(rng.choice(sets), k=rng.randint(shortest, 48))) for _ in range(n)]


def half(items: list[str], which: int, fewest: int = 2000) -> list[str]:
    """One of two disjoint halves, by a checksum; of a list too short to be split, all."""
    return [x for x in items if zlib.crc32(x.encode()) % 2 == which] if len(items) >= fewest else items


def identifiers(n: int, seed: int = 8, words: list[str] = WORDS) -> list[str]:
    rng, out = random.Random(seed), []
    while len(out) < n:
        parts = rng.choices(words, k=rng.randint(2, 5))
        style = rng.randrange(5)
        name = "_".join(parts) if style == 0 else "-".join(parts) if style == 1 else "/".join(parts) if style == 2 else parts[0] + "".join(w.capitalize() for w in parts[1:]) if style == 3 else "_".join(parts).upper()
        tail = rng.choice(["", "", "", str(rng.randint(0, 99)), f"_{rng.randint(1, 9999)}", f"-{rng.randint(1990, 2030)}-{rng.randint(10, 12)}-{rng.randint(10, 28)}"])
        out += [name + tail] if len(name + tail) >= 12 else []
    return out


def words_of(vocabulary: str) -> list[str]:
    """The lower-case ASCII words of three and more letters among a tokenizer's tokens (its file of tokens and ranks)."""
    tokens = (token.decode("latin-1").strip().lower() for token in read_ranks(vocabulary))
    return sorted({t for t in tokens if re.fullmatch("[a-z]{3,}", t)})


def long_words(n: int, seed: int = 9, words: list[str] = WORDS) -> list[str]:
    """Words of 12 letters and more: one, two or three run together, or letter groups; small, capitalised or capital."""
    rng, out = random.Random(seed), []
    while len(out) < n:
        word = "".join(rng.choices(words, k=rng.randint(1, 3)) if rng.random() < 0.5 else rng.choices(GROUPS, k=rng.randint(3, 9)))
        out += [rng.choice([word, word, word.capitalize(), word.upper()])] if len(word) >= 12 else []
    return out


class MarkovModel:
    """log P(next | two before), with add-``smooth`` counts backed by the order-1 model."""

    def __init__(self, samples: list[str], smooth: float = 0.5):
        size, two, one = len(ALPHABET), {}, {}
        for s in samples:
            padded = "\0\0" + s
            for k in range(2, len(padded)):
                two.setdefault(padded[k - 2 : k], {}).setdefault(padded[k], 0)
                two[padded[k - 2 : k]][padded[k]] += 1
                one.setdefault(padded[k - 1], {}).setdefault(padded[k], 0)
                one[padded[k - 1]][padded[k]] += 1
        self.two, self.one, self.smooth, self.size = two, one, smooth, size
        self.two_sum = {k: sum(v.values()) for k, v in two.items()}
        self.one_sum = {k: sum(v.values()) for k, v in one.items()}

        self.known: dict[str, float] = {}  # at most as many as there are triples of key characters

    def log_likelihood(self, s: str) -> float:
        padded, total, known = "\0\0" + s, 0.0, self.known
        for k in range(len(s)):
            triple = padded[k : k + 3]
            value = known.get(triple)
            if value is None:
                value = known[triple] = self._log(triple)
            total += value
        return total

    def _log(self, triple: str, strength: float = 4.0) -> float:
        pair, before, char = triple[:2], triple[1], triple[2]
        p1 = (self.one.get(before, {}).get(char, 0) + self.smooth) / (self.one_sum.get(before, 0) + self.smooth * self.size)
        return math.log((self.two.get(pair, {}).get(char, 0) + strength * p1) / (self.two_sum.get(pair, 0) + strength))


class Scanner:
    """The models and their limits. ``positive`` and ``negative`` are labelled tokens, of which the odd ones train and the even ones set the limits."""

    def __init__(self, positive: list[str] | None = None, negative: list[str] | None = None, alarms: float = 0.001, words: list[str] = WORDS, samples: int = 20_000):
        fit = lambda given, made: given[1::2] if given is not None else made(0)
        check = lambda given, made: given[::2] if given is not None else made(1)
        secrets = lambda k: random_strings(samples, 7 + 100 * k)
        names = lambda k: identifiers(samples, 8 + 100 * k, half(words, k))
        prose = lambda k: long_words(samples, 9 + 100 * k, half(words, k))
        self.random, self.ordinary, self.words = MarkovModel(fit(positive, secrets)), MarkovModel(fit(negative, names)), MarkovModel(prose(0))
        wanted, usual = check(positive, secrets), check(negative, names) + prose(1)
        letters = random.Random(10)
        wanted = wanted + ["".join(letters.choices(ALPHABET[a : a + 26], k=letters.randint(12, 32))) for a in (0, 26) for _ in range(samples // 4)]
        self.limits = [self._limit([x for x in wanted if self.like_prose(x) == k], [x for x in usual if self.like_prose(x) == k], alarms) for k in (False, True)]

    @staticmethod
    def like_prose(token: str) -> bool:
        return PROSE.fullmatch(token) is not None

    def _limit(self, wanted: list[str], usual: list[str], alarms: float) -> tuple[float, float]:
        """(slope, offset) with the most hits among the wanted tokens and at most a share ``alarms`` of the usual ones; the higher limit of equal ones."""
        best = (-1.0, 0.0, 0.0)
        of_wanted, of_usual = ([(self.ratio(x), len(x)) for x in xs] for xs in (wanted, usual))
        for slope in (0.0, 0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.8, 1.0):
            over = sorted((r - slope * n for r, n in of_usual), reverse=True)
            offset = max(0.0, over[min(int(alarms * len(over)), len(over) - 1)] if over else 0.0)
            hits = sum(r > slope * n + offset for r, n in of_wanted) / max(len(of_wanted), 1)
            best = max(best, (hits, slope, offset))
        return best[1:]

    def ratio(self, token: str) -> float:
        """Log-likelihood ratio, above 0: more like a random string."""
        ordinary = self.ordinary.log_likelihood(token)
        if self.like_prose(token):
            ordinary = max(ordinary, self.words.log_likelihood(token))
        return self.random.log_likelihood(token) - ordinary

    def secret(self, token: str) -> bool:
        slope, offset = self.limits[self.like_prose(token)]
        return self.ratio(token) > slope * len(token) + offset

    def base(self, text: str) -> list[tuple[int, int, int]]:
        spans = [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 12]
        if "AKIA" in text:
            spans += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 18]
        spans += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
        return sorted(spans)

    def added(self, text: str, base: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
        out, k, reach = [], 0, 0  # reach: the furthest end of the base spans that start no later than the candidate
        for m in CANDIDATE.finditer(text):
            while k < len(base) and base[k][0] <= m.start():
                reach = max(reach, base[k][2])
                k += 1
            if reach < m.end() and self.secret(m.group()):
                out.append((m.start(), 3, m.end()))
        return out


def joined(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in sorted(spans))


def find_secrets(docs: DataFrame, *, positive: list[str] | None = None, negative: list[str] | None = None, alarms: float = 0.001, words: list[str] | None = None) -> DataFrame:
    """One row per document: doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_markov."""
    scanner = Scanner(positive, negative, alarms, words or WORDS)
    id_type = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for text in batch.column(1).to_pylist():
                base = scanner.base(text)
                more = scanner.added(text, base)
                kinds = [k for _, k, _ in base]
                rows.append((kinds.count(0), kinds.count(1), kinds.count(2), hashlib.sha256(joined(base).encode()).hexdigest(), joined(base + more), len(more)))
            cols = list(zip(*rows, strict=True)) if rows else [()] * 6
            types = [pa.int64()] * 3 + [pa.string()] * 2 + [pa.int64()]
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, t) for c, t in zip(cols, types, strict=True))], names)

    names = ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_markov"]
    return docs.select("doc_id", text_of().alias("text")).mapInArrow(run, f"doc_id {id_type}, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_markov long")
