"""Toxicity: gradient-boosted trees over dense features, calibrated by isotonic regression.

Features per text: densities and counts of lexicon words (two tiers, learned from labelled training rows
as words whose document log odds are high), lexicon words within three words of a second-person word,
shares of capitals, digits, exclamation and other punctuation, repeated letters, and words that match the
lexicon only after obfuscation is undone. In training a document's own counts are taken out of the
lexicon first, so features look as they will on unseen rows.

Fit on at most `bound` labelled rows (those with the smallest id hash), on the driver; every row is scored
where it is read, in one narrow Arrow pass.

Defined cases: null or empty text has zero features and gets a score like any row; without labelled rows
of both kinds every score is the share of positives (0 if none); repeated rows score alike; labels, lang,
source and doc_id are never inputs; further columns are ignored (query) or kept (filter).
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Collection, Iterable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import give_back, map_columns, remainder, remainder_col, rewrite_batches, sample_rows

BOUND = 6000
# Second-person words of English, German, French and Spanish.
SECOND_PERSON = frozenset(
    "you your yours yourself u ur du dich dir dein deine euch euer ihr tu te toi ton ta tes vous votre vos "
    "tú ti tu tus usted ustedes vosotros".split()
)
# Characters that stand for letters in obfuscated words.
UNMASK = str.maketrans({"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "@": "a", "$": "s", "!": "i"})
INNER = re.compile(r"[^\w]|_")
REPEAT = re.compile(r"(\w)\1{2,}")
EDGE = ".,;:!?\"'()[]{}*%&$#|<>-_/\\"
FEATURES = 14


class Lexicon:
    """Document counts of words in labelled rows; which words are in it when one row is left out."""

    def __init__(self, rows: Iterable[tuple[Collection[str], int]], strong: float = 2.0, weak: float = 1.0, least: int = 3, share: float = 0.01):
        self.n = [0, 0]
        seen = [Counter(), Counter()]
        for words, y in rows:
            self.n[y] += 1
            seen[y].update(words)
        self.strong, self.weak, self.least = strong, weak, max(least, share * self.n[1])
        self.seen = {w: (seen[0][w], c) for w, c in seen[1].items() if c >= self.least}
        self.tiers = {w: t for w in self.seen if (t := self.tier(w, *self.seen[w], *self.n))}

    def tier(self, word: str, clean: int, toxic: int, n_clean: int, n_toxic: int) -> int:
        if toxic < self.least:
            return 0
        odds = math.log((toxic + 0.5) / (n_toxic + 1)) - math.log((clean + 0.5) / (n_clean + 1))
        odds -= 1.5 * math.sqrt(1 / (toxic + 0.5) + 1 / (clean + 0.5))  # a low bound: rare words must not enter by chance
        return 2 if odds >= self.strong else 1 if odds >= self.weak else 0

    def without(self, words: Collection[str], y: int) -> dict[str, int]:
        """The tiers of these words as they are without one training row that holds them."""
        out = {}
        for w in words:
            if w in self.seen:
                c, t = self.seen[w]
                if tier := self.tier(w, c - (y == 0), t - (y == 1), self.n[0] - (y == 0), self.n[1] - (y == 1)):
                    out[w] = tier
        return out


def words_of(text: str) -> list[str]:
    return [w.strip(EDGE) for w in text.lower().split()]


def features(text: str | None, tiers: dict[str, int], words: list[str] | None = None) -> list[float]:
    if not text:
        return [0.0] * FEATURES
    words = words_of(text) if words is None else words
    n, chars = max(1, len(words)), np.frombuffer(text.encode("utf-32-le"), np.uint32)
    hits = [(i, t) for i, w in enumerate(words) if (t := tiers.get(w))]
    strong = [i for i, t in hits if t == 2]
    near = sum(any(x in SECOND_PERSON for x in words[max(0, i - 3) : i + 4]) for i, _ in hits)
    masked = 0
    for w in set(words):
        if w not in tiers and not w.isalpha() and len(w) < 40:
            plain = INNER.sub("", w.translate(UNMASK))
            masked += plain in tiers
    m, counts = max(1, len(chars)), np.bincount(np.minimum(chars, 128), minlength=129)
    upper, digits, space = counts[65:91].sum(), counts[48:58].sum(), counts[9:14].sum() + counts[32]
    letters = max(1, counts[97:123].sum() + upper + counts[128])
    marks = m - letters - digits - space
    return [
        len(strong) / n,
        len(hits) / n,
        np.log1p(len(strong)),
        np.log1p(len(hits) - len(strong)),
        len({words[i] for i in strong}),
        near / n,
        np.log1p(near),
        masked / n,
        upper / letters,
        counts[33] / m,
        marks / m,
        digits / m,
        len(REPEAT.findall(text)) / n,
        np.log1p(n),
    ]


class Trees:
    """Boosted regression trees on the logistic loss, on quantile bins."""

    def __init__(self, rounds: int = 80, depth: int = 3, rate: float = 0.15, bins: int = 32, ridge: float = 2.0, leaf: int = 4):
        self.rounds, self.depth, self.rate, self.bins, self.ridge, self.leaf = rounds, depth, rate, bins, ridge, leaf

    def fit(self, x: np.ndarray, y: np.ndarray) -> Trees:
        q = np.linspace(0, 1, self.bins + 1)[1:-1]
        self.cuts = [np.unique(np.quantile(x[:, j], q)) for j in range(x.shape[1])]
        b = np.stack([np.searchsorted(c, x[:, j], side="right") for j, c in enumerate(self.cuts)], 1)
        p = np.clip(y.mean(), 1e-3, 1 - 1e-3)
        self.start, self.trees = float(np.log(p / (1 - p))), []
        margin = np.full(len(y), self.start)
        for _ in range(self.rounds):
            p = 1 / (1 + np.exp(-margin))
            tree = []
            self._grow(tree, b, y - p, p * (1 - p), np.arange(len(y)), 0)
            self.trees.append(tree)
            margin += self._tree(tree, b)
        return self

    def _grow(self, tree, b, g, h, rows, depth) -> int:
        at, total_g, total_h = len(tree), g[rows].sum(), h[rows].sum()
        tree.append([-1, 0, 0, 0, self.rate * total_g / (total_h + self.ridge)])
        best = (1e-4, -1, 0)
        if depth < self.depth and len(rows) >= 2 * self.leaf:
            base = total_g**2 / (total_h + self.ridge)
            for j in range(b.shape[1]):
                k = len(self.cuts[j]) + 1
                if k < 2:
                    continue
                gs, hs, ns = (np.cumsum(np.bincount(b[rows, j], v, k))[:-1] for v in (g[rows], h[rows], None))
                gain = gs**2 / (hs + self.ridge) + (total_g - gs) ** 2 / (total_h - hs + self.ridge) - base
                gain[(ns < self.leaf) | (len(rows) - ns < self.leaf)] = 0
                s = int(gain.argmax())
                if gain[s] > best[0]:
                    best = (gain[s], j, s)
        if best[1] >= 0:
            _, j, s = best
            goes = b[rows, j] <= s
            tree[at][:3] = j, s, self._grow(tree, b, g, h, rows[goes], depth + 1)
            tree[at][3] = self._grow(tree, b, g, h, rows[~goes], depth + 1)
        return at

    def _tree(self, tree, b) -> np.ndarray:
        t = np.array(tree)
        at = np.zeros(len(b), int)
        for _ in range(self.depth):
            j = t[at, 0].astype(int)
            down = np.where(b[np.arange(len(b)), np.maximum(j, 0)] <= t[at, 1], t[at, 2], t[at, 3]).astype(int)
            at = np.where(j >= 0, down, at)
        return t[at, 4]

    def margin(self, x: np.ndarray) -> np.ndarray:
        b = np.stack([np.searchsorted(c, x[:, j], side="right") for j, c in enumerate(self.cuts)], 1)
        return self.start + sum(self._tree(t, b) for t in self.trees)


def isotonic(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pooled adjacent violators: knots of the least-squares nondecreasing map from x to y; equal x are one
    weighted point, so the order of rows doesn't matter."""
    at, place, weight = np.unique(x, return_inverse=True, return_counts=True)
    mean = np.bincount(place, y, len(at)) / weight
    blocks: list[list[float]] = []  # mean, weight, least x, most x
    for v, t, n in zip(at, mean, weight):
        blocks.append([t, n, v, v])
        while len(blocks) > 1 and blocks[-2][0] >= blocks[-1][0]:
            m, w, _, hi = blocks.pop()
            a = blocks[-1]
            a[0], a[1], a[3] = (a[0] * a[1] + m * w) / (a[1] + w), a[1] + w, hi
    xs = [v for b in blocks for v in b[2:]]
    ys = [b[0] for b in blocks for _ in range(2)]
    return np.array(xs), np.array(ys)


class Model:
    def __init__(self, rows: list[tuple[str | None, int]]):
        """rows: (text, label). Two thirds grow the trees, one third calibrates them. The driver holds the words of one
        text at a time: texts are split again for their features."""
        lexicon = Lexicon((set(words_of(t or "")), int(y)) for t, y in rows)
        self.tiers, self.prior, self.trees = lexicon.tiers, float(np.mean([int(y) for _, y in rows])) if rows else 0.0, None
        if len({int(y) for _, y in rows}) == 2:

            def left_out(t: str | None, y: int) -> list[float]:
                words = words_of(t or "")
                return features(t, lexicon.without(set(words), y), words)

            x = np.array([left_out(t, int(y)) for t, y in rows])
            y = np.array([int(y) for _, y in rows], float)
            third = np.arange(len(y)) % 3
            grow, rest = (third < 2, third == 2) if y[third < 2].sum() >= 4 and y[third == 2].sum() >= 4 else (third >= 0, third >= 0)
            self.trees = Trees().fit(x[grow], y[grow])
            m = self.trees.margin(x[rest])
            self.knots = isotonic(m, y[rest])

    def scores(self, texts: list[str | None]) -> np.ndarray:
        if self.trees is None or not texts:
            return np.full(len(texts), self.prior)
        m = self.trees.margin(np.array([features(t, self.tiers) for t in texts]))
        smooth = 1 / (1 + np.exp(-m))  # keeps the order within the calibrated steps
        return np.clip(0.98 * np.interp(m, *self.knots) + 0.02 * smooth, 0, 1)


def fit(docs: DataFrame, labels: DataFrame, bound: int = BOUND) -> Model:
    """A model from at most `bound` labelled rows outside the held-out fifth; a doc_id labelled twice counts once
    (toxic if any label is), a doc_id of several rows by its least text."""
    known = labels.where("toxic is not null and doc_id is not null").where(remainder_col("doc_id", 5) != 0)
    known = known.groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    want = {r["doc_id"]: int(r["toxic"] > 0) for r in sample_rows(known, "doc_id", bound)}
    spark = docs.sparkSession
    ids = spark.createDataFrame([(i,) for i in want], "doc_id long")
    rows = docs.select("doc_id", "text").join(F.broadcast(ids), "doc_id", "left_semi").groupBy("doc_id").agg(F.min("text").alias("text")).collect()
    model = Model([(r["text"], want[r["doc_id"]]) for r in sorted(rows, key=lambda r: r["doc_id"])])
    del rows
    return give_back(model)


def score(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, held_out, score, predicted."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        def step(cols):
            s = shared.value.scores(cols["text"])
            held = [i is not None and remainder(i, 5) == 0 for i in cols["doc_id"]]
            yield {"doc_id": cols["doc_id"], "held_out": held, "score": s.tolist(), "predicted": (s >= 0.5).astype(int).tolist()}

        return step

    return map_columns(docs, ["doc_id", "text"], "doc_id long, held_out boolean, score double, predicted int", make)


def drop_toxic(docs: DataFrame, model: Model, threshold: float = 0.5) -> DataFrame:
    """The documents scored below the threshold, with all their columns."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        def step(batch):
            s = shared.value.scores(batch.column(batch.schema.get_field_index("text")).to_pylist())
            return batch.filter(pa.array(s < threshold))

        return step

    return rewrite_batches(docs, make)
