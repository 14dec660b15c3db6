"""Toxicity by weak supervision.

Voters (lexicons, word stems and patterns) each say toxic, clean or nothing about a document. A generative label model explains
their votes over the whole corpus: each voter has an accuracy per class, and correlated voters are tied in a tree, so that what one voter
merely repeats is not counted twice. The model is fitted by expectation maximisation on the counts of vote vectors (all
documents; a handful of numbers at any corpus size), which the votes of the labelled sample, their classes fixed, anchor with a weight of ``anchor`` times the corpus (0:
not at all). Its posteriors are the soft labels on which a logistic regression over words, stems and surface measures is trained; that classifier gives the scores.

Lexicons are mined from a bounded sample of labelled rows (``sample`` rows in hash order, ``crc32(doc_id) mod folds`` not 0), beside a short
public list of insults. The same sample, with its posteriors, trains the classifier. Everything else covers all documents and whole texts.

Defined cases: null text counts as empty; empty texts get the score of a document without any word; an empty table gives no rows; without labelled rows the
voters fall back to the public list and patterns; labels that are repeated or not in the documents change nothing, nor do repeated rows of a labelled document (the smallest of
their texts is used); rows with a null id are scored like any others, are never held out and never learnt from; equal texts get equal scores; other columns are ignored.
"""

from __future__ import annotations

import math
import re
import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import text_of

#: Common insults of four languages; fixed values.
INSULTS = frozenset(
    "idiot moron stupid loser scum trash pathetic worthless disgusting clown dumb fool bastard imbecile "
    "idiota estúpido imbécil basura asqueroso idiote crétin connard ordure stupide dumm trottel arschloch abschaum".split()
)
SECOND_PERSON = frozenset("you your youre tu te vous toi du dich dir ihr usted tú ti".split())
WORD = re.compile(r"\w+")
STEMS = (4, 5, 6, 7, 8)
#: Patterns of abuse that need no lexicon, each with words of which a text must hold one (none: any text with such a sign): fixed values.
PATTERNS = {
    "told off": (
        frozenset("shut lost hell dead screw hate gueule ferme foutre klappe maul verpiss cállate vete odio".split()),
        re.compile(r"\b(shut up|get lost|go to hell|drop dead|screw you|hate you|ta gueule|ferme[- ]la|va te faire foutre|halt die klappe|halt's maul|verpiss dich|cállate|vete a la|te odio)\b"),
    ),
    "called names": (INSULTS, re.compile(r"\b(you|you're|your|tu es|espèce de|du bist|ihr|eres|sois)\s+(\w+\s+)?(" + "|".join(sorted(INSULTS)) + r")\b")),
    "masked": (frozenset(), re.compile(r"\b[a-z]\*+[a-z]+\b|\b[a-z]{1,2}[@#$]{2,}[a-z]+\b")),
    "wished away": (frozenset({"should", "must", "deserve"}), re.compile(r"\b(people|women|men|they|you|all)\s+(like\s+you\s+)?(should|must|deserve\s+to)\s+(die|rot|suffer|disappear)\b")),
}
SIGNS = re.compile(r"[*@#$][a-z]")
VOTERS = ("public list", "mined words", "mined stems", "weak words", "two or more", "dense", "addressed", "repeated", *PATTERNS, "no sign")


def held_out(doc_id: Column, folds: int = 5) -> Column:
    return F.crc32(doc_id.cast("string")) % folds == 0


class Lexicons:
    """Signs mined from labelled texts: words and stems that mark toxic texts strongly, and weak ones.

    A sign's support is counted over groups of near-equal texts, so that the words of a text with many copies are not taken for insults,
    and signs are chosen greedily, each by the groups that fewer than ``cover`` signs chosen before explain.
    """

    def __init__(self, texts: list[str], toxic: np.ndarray, most: int = 300):
        self.words, self.stems, self.weak, self.vocabulary = frozenset(), {}, frozenset(), {}
        positive = int(toxic.sum())
        negative = len(texts) - positive
        if not positive or not negative:
            return
        group = self._groups([texts[k] for k in np.flatnonzero(toxic)])
        positive = len(set(group))
        least = max(3, positive // 200)
        where: dict[tuple[int, str], set[int]] = {}
        for k, g in zip(np.flatnonzero(toxic), group, strict=True):
            for sign in self._signs(texts[k]):
                where.setdefault(sign, set()).add(g)
        where = {s: at for s, at in where.items() if len(at) >= least}
        clean = Counter()
        for k in np.flatnonzero(toxic == 0):
            clean.update(s for s in self._signs(texts[k]) if s in where)
        odds = {s: math.log((len(at) + 0.5) / (positive + 1)) - math.log((clean[s] + 0.5) / (negative + 1)) for s, at in where.items()}
        strong, open_groups = self._greedy(where, odds, 3.5, dict.fromkeys(group, 3), least, most)
        weak, _ = self._greedy({s: at for s, at in where.items() if s[0] == 0}, odds, 2.0, open_groups, least, most)
        self.words = frozenset(s for n, s in strong if n == 0)
        self.stems = {n: frozenset(s for m, s in strong if m == n) for n in STEMS if any(m == n for m, _ in strong)}
        self.weak = frozenset(s for _, s in weak)
        self.vocabulary = {sign: k for k, sign in enumerate(strong + weak)}

    @staticmethod
    def _signs(text: str) -> set[tuple[int, str]]:
        found = set(WORD.findall(text.lower()))
        return {(0, w) for w in found} | {(n, w[:n]) for w in found for n in STEMS if len(w) > n}

    @staticmethod
    def _groups(texts: list[str], size: int = 16, same: int = 6) -> list[int]:
        """A number for each text, equal for texts of which ``same`` of ``size`` MinHash values of their words agree."""
        salts, seen, out = [f"{k}:" for k in range(size)], {}, []
        for text in texts:
            words = set(WORD.findall(text.lower())) or {""}
            own = [(k, min(zlib.crc32((salt + w).encode()) for w in words)) for k, salt in enumerate(salts)]
            votes = Counter(g for x in own if (g := seen.get(x)) is not None)
            best, n = votes.most_common(1)[0] if votes else (len(out), 0)
            out.append(best if n >= same else len(out))
            for x in own:
                seen.setdefault(x, out[-1])
        return out

    @staticmethod
    def _greedy(where, odds, bar, open_groups, least, most) -> tuple[list[tuple[int, str]], dict[int, int]]:
        """``open_groups``: how many more signs each group may still call for."""
        left, chosen, open_groups = {s: at for s, at in where.items() if odds[s] > bar + (s[0] > 0)}, [], dict(open_groups)
        while left and len(chosen) < most:
            gains = {s: sum(g in open_groups for g in at) for s, at in left.items()}
            left = {s: at for s, at in left.items() if gains[s] >= least}
            if not left:
                break
            best = max(left, key=lambda s: (gains[s] * odds[s], -s[0], s[1]))
            for g in left.pop(best):
                if g in open_groups:
                    open_groups[g] -= 1
                    if not open_groups[g]:
                        del open_groups[g]
            chosen.append(best)
        return chosen, open_groups

    def look(self, text: str) -> tuple[list[int], list[int], list[float]]:
        """(votes, signs of the vocabulary, surface measures) of a text."""
        text = text.lower()
        words = WORD.findall(text)
        found = set(words)
        public, mined, weak = found & INSULTS, found & self.words, found & self.weak
        rooted = {(n, x) for n, stems in self.stems.items() for x in stems & {w[:n] for w in found if len(w) > n}}
        strong = public | mined
        if rooted:
            strong = strong | {w for w in found if any(len(w) > n and w[:n] == x for n, x in rooted)}
        hits = sum(map(words.count, strong)) if len(strong) < 8 else sum(w in strong for w in words)
        kinds = len(public | mined) + len(rooted)
        addressed = bool(strong) and any(w in SECOND_PERSON and any(x in strong for x in words[k + 1 : k + 4]) for k, w in enumerate(words))
        share = hits / len(words) if words else 0.0
        votes = [int(bool(public)), int(bool(mined)), int(bool(rooted)), int(bool(weak)), int(kinds >= 2), int(share > 0.004), int(addressed), int(hits >= 2)]
        matched = [int((not found.isdisjoint(words) if words else SIGNS.search(text) is not None) and pattern.search(text) is not None) for words, pattern in PATTERNS.values()]
        votes += [*matched, -int(not kinds and not any(matched))]
        signs = [self.vocabulary[s] for s in [*((0, w) for w in mined | weak), *rooted]]
        return votes, signs, [min(share, 0.1) * 50, float(kinds > 0), math.log1p(kinds)]


class LabelModel:
    """P(class) * product over voters of P(vote | vote of its parent in the tree, class), fitted by expectation maximisation.

    Vote vectors of labelled rows can anchor the fit: together they weigh as much as the corpus, with their classes fixed.
    """

    def __init__(self, prior: float = 0.1, rounds: int = 30, smooth: float = 1.0):
        self.prior, self.rounds, self.smooth = prior, rounds, smooth

    def fit(self, votes: np.ndarray, counts: np.ndarray, known_votes: np.ndarray | None = None, known: np.ndarray | None = None, anchor: float = 1.0) -> LabelModel:
        counts, free = counts.astype(float), len(votes)
        if known is not None and len(known) and anchor:
            votes = np.concatenate([votes, known_votes])
            counts = np.concatenate([counts, np.full(len(known), anchor * counts.sum() / len(known))])
        else:
            known = np.zeros(0)
        states = votes + 1
        n, m = states.shape
        # the start: a vote counts for its class with a fixed log-odds; each voter alike
        post = 1 / (1 + np.exp(-(votes.sum(1) * 1.0 + math.log(self.prior / (1 - self.prior)))))
        self.parent = [-1] * m
        post[free:] = known
        for step in range(self.rounds):
            if step in (0, 3, 10):
                self.parent = self._tree(states, counts, post, m)
            self.table = []
            weight = np.stack([counts * (1 - post), counts * post], 1)
            self.prior = float(np.clip(weight[:, 1].sum() / max(counts.sum(), 1e-9), 1e-3, 0.6))
            for j in range(m):
                above = states[:, self.parent[j]] if self.parent[j] >= 0 else np.zeros(n, int)
                table = np.full((2, 3, 3), self.smooth / 3)
                for y in (0, 1):
                    np.add.at(table[y], (above, states[:, j]), weight[:, y])
                self.table.append(np.log(table / table.sum(2, keepdims=True)))
            post = self.posterior(votes)
            post[free:] = known
        return self

    def _tree(self, states, counts, post, m) -> list[int]:
        """Spanning tree of greatest mutual information given the class; an edge stands only if the voters are really correlated."""
        info = np.zeros((m, m))
        for y, w in ((0, counts * (1 - post)), (1, counts * post)):
            for a in range(m):
                for b in range(a):
                    joint = np.full((3, 3), 1e-9)
                    np.add.at(joint, (states[:, a], states[:, b]), w)
                    p = joint / joint.sum()
                    info[a, b] += w.sum() * (p * np.log(p / (p.sum(1, keepdims=True) * p.sum(0, keepdims=True)))).sum()
        info = (info + info.T) / max(counts.sum(), 1e-9)
        parent, inside = [-1] * m, {0}
        while len(inside) < m:
            gain, a, b = max((info[a, b], -a, -b) for a in range(m) if a not in inside for b in inside)
            parent[-a] = -b if gain > 1e-4 else -1
            inside.add(-a)
        self.information = info
        return parent

    def posterior(self, votes: np.ndarray) -> np.ndarray:
        states = votes + 1
        log_odds = np.full(len(votes), math.log(self.prior / (1 - self.prior)))
        for j, table in enumerate(self.table):
            above = states[:, self.parent[j]] if self.parent[j] >= 0 else np.zeros(len(votes), int)
            log_odds += table[1][above, states[:, j]] - table[0][above, states[:, j]]
        return 1 / (1 + np.exp(-np.clip(log_odds, -30, 30)))


def fit_logistic(signs: list[list[int]], dense: np.ndarray, target: np.ndarray, size: int, rounds: int = 300, decay: float = 1e-4) -> np.ndarray:
    """Weights (signs, dense measures, bias) of a logistic regression on soft labels; full-batch Adam, classes weighted evenly."""
    width = size + dense.shape[1] + 1
    x = np.zeros((len(target), width), np.float32)
    for k, own in enumerate(signs):
        x[k, own] = 1
    x[:, size : size + dense.shape[1]] = dense
    x[:, -1] = 1
    share = float(np.clip(target.mean(), 1e-3, 1 - 1e-3))
    weight = (target * 0.5 / share + (1 - target) * 0.5 / (1 - share)).astype(np.float32)
    w, m, v = np.zeros(width), np.zeros(width), np.zeros(width)
    for step in range(1, rounds + 1):
        p = 1 / (1 + np.exp(-np.clip(x @ w.astype(np.float32), -30, 30)))
        g = x.T @ (weight * (p - target)) / len(target) + decay * w
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        w -= 0.1 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
    return w


def _mapped(docs: DataFrame, lexicons: Lexicons, each, schema: str) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield each(batch, lexicons)

    return docs.mapInArrow(run, schema)


def vote_counts(docs: DataFrame, lexicons: Lexicons) -> tuple[np.ndarray, np.ndarray]:
    """The vote vectors found in the corpus and how often; at most 2 ** voters rows, whatever the corpus."""

    def each(batch: pa.RecordBatch, lex: Lexicons) -> pa.RecordBatch:
        counts = Counter(",".join(map(str, lex.look(t)[0])) for t in batch.column(0).to_pylist())
        return pa.RecordBatch.from_arrays([pa.array(list(counts), pa.string()), pa.array(list(counts.values()), pa.int64())], ["votes", "n"])

    rows = _mapped(docs.select(text_of().alias("text")), lexicons, each, "votes string, n long").groupBy("votes").agg(F.sum("n").alias("n")).collect()
    rows.sort()
    return np.array([list(map(int, r["votes"].split(","))) for r in rows]).reshape(-1, len(VOTERS)), np.array([r["n"] for r in rows])


def labelled_sample(docs: DataFrame, labels: DataFrame, sample: int, folds: int) -> tuple[list[str], np.ndarray]:
    """Texts and labels of at most ``sample`` rows outside the held-out fold, in the order of a hash of the id."""
    chosen = labels.filter(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"), folds)).select("doc_id", "toxic").distinct().orderBy(F.xxhash64("doc_id"), "doc_id", "toxic").limit(sample)
    rows = docs.select("doc_id", text_of().alias("text")).join(F.broadcast(chosen), "doc_id").groupBy("doc_id", "toxic").agg(F.min("text").alias("text")).collect()
    rows.sort(key=lambda r: (r["doc_id"], r["toxic"], r["text"]))
    return [r["text"] for r in rows], np.array([int(r["toxic"] == 1) for r in rows], int)


class ToxicityModel:
    def __init__(self, lexicons: Lexicons, label_model: LabelModel, weights: np.ndarray):
        self.lexicons, self.label_model, self.weights = lexicons, label_model, weights

    def score(self, text: str) -> float:
        _, signs, dense = self.lexicons.look(text)
        size = len(self.lexicons.vocabulary)
        z = self.weights[-1] + sum(self.weights[k] for k in signs) + float(np.dot(self.weights[size:-1], dense))
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))


def fit(docs: DataFrame, labels: DataFrame, *, sample: int = 8000, folds: int = 5, anchor: float = 1.0) -> ToxicityModel:
    texts, toxic = labelled_sample(docs, labels, sample, folds)
    lexicons = Lexicons(texts, toxic)
    votes, counts = vote_counts(docs, lexicons)
    model = LabelModel(prior=float(np.clip(toxic.mean(), 0.01, 0.5)) if len(toxic) else 0.1)
    looks = [lexicons.look(t) for t in texts]
    own = np.array([v for v, _, _ in looks], int).reshape(-1, len(VOTERS))
    model.fit(votes if len(votes) else np.zeros((1, len(VOTERS)), int), counts if len(counts) else np.ones(1), own, toxic, anchor)
    if looks:
        target = model.posterior(own)
        weights = fit_logistic([s for _, s, _ in looks], np.array([d for _, _, d in looks]), target, len(lexicons.vocabulary))
    else:  # no labelled row: the public list alone decides
        weights = np.array([0.0, 6.0, 0.0, -3.0])
    return ToxicityModel(lexicons, model, weights)


def score_documents(docs: DataFrame, model: ToxicityModel, *, folds: int = 5) -> DataFrame:
    """One row per document: doc_id, held_out, score, predicted."""
    id_type = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            scores = [model.score(t) for t in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(scores, pa.float64()), pa.array([int(s >= 0.5) for s in scores], pa.int32())], ["doc_id", "held_out", "score", "predicted"])

    rows = docs.select("doc_id", F.coalesce(held_out(F.col("doc_id"), folds), F.lit(False)).alias("held_out"), text_of().alias("text"))
    return rows.mapInArrow(run, f"doc_id {id_type}, held_out boolean, score double, predicted int")


def drop_toxic(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """``docs`` without the rows whose own text the classifier scores at 0.5 or more."""
    model = fit(docs, labels, **options)
    schema = docs.schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = [model.score(t or "") < 0.5 for t in batch.column(batch.schema.get_field_index("text")).cast(pa.string()).to_pylist()]
            yield batch.filter(pa.array(keep, pa.bool_()))

    return docs.mapInArrow(run, schema)
