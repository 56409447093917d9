"""Language ID: string-kernel classification with Nystroem landmarks.

The kernel is the blended spectrum of character n-grams (1 to 3) by presence: the number of n-grams two
texts share over the root of the product of their counts, on n-grams hashed to a fixed number of slots.
Kernel ridge regression, one language against the rest, is solved in the span of the landmark texts.
Since the kernel is an inner product, landmark columns and dual weights fold into one matrix of slots by
languages, and a batch of texts is scored by one matrix product with its presence rows.

Fit on at most `bound` labelled rows outside the held-out quarter (smallest id hash), on the driver; every
whole text is scored where it is read.

Defined cases: null text and text without letters are `und` with score 0; without labelled rows every text
is `und`; ties take the first language in order; repeated rows score alike; lang, source and doc_id are
never inputs; further columns are ignored.
"""

from __future__ import annotations

import re

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_columns, remainder, remainder_col, sample_rows

BOUND, LANDMARKS, SLOT_BITS, ORDERS = 2000, 192, 14, (1, 2, 3)
LETTER = re.compile(r"[^\W\d_]")
_MUL = (np.uint32(2654435761), np.uint32(2246822519), np.uint32(3266489917))


def presence(texts: list[str | None], bits: int = SLOT_BITS, orders: tuple[int, ...] = ORDERS) -> np.ndarray:
    """Rows of 0/1 by slot, scaled to length one."""
    out = np.zeros((len(texts), 1 << bits), np.float32)
    for row, text in zip(out, texts):
        code = np.frombuffer((text or "").lower().encode("utf-32-le"), np.uint32)
        for n in orders:
            if len(code) >= n:
                h = code[: len(code) - n + 1] * _MUL[0] + np.uint32(n)
                for k in range(1, n):
                    h = (h ^ (h >> np.uint32(15))) * _MUL[1] + code[k : len(code) - n + 1 + k] * _MUL[2]
                row[(h ^ (h >> np.uint32(13))) * _MUL[0] >> np.uint32(32 - bits)] = 1
    return out / np.sqrt(np.maximum(1, out.sum(1, keepdims=True)))


class Model:
    def __init__(self, rows: list[tuple[str, str]], landmarks: int = LANDMARKS, ridge: float = 1e-2, bits: int = SLOT_BITS):
        """rows: (text, language)."""
        self.bits, self.langs = bits, sorted({lang for _, lang in rows})
        if not rows:
            return
        pick = np.unique(np.linspace(0, len(rows) - 1, landmarks).astype(int))
        marks = presence([rows[i][0] for i in pick], bits)
        k = np.vstack([presence([t for t, _ in rows[s : s + 256]], bits) @ marks.T for s in range(0, len(rows), 256)]).astype(np.float64)
        y = np.array([[1.0 if lang == x else -1.0 for x in self.langs] for _, lang in rows])
        inner = k[pick]
        values, vectors = np.linalg.eigh((inner + inner.T) / 2)
        good = values > 1e-8 * values.max()
        root = vectors[:, good] / np.sqrt(values[good])
        z = np.hstack([k @ root, np.ones((len(rows), 1))])
        w = np.linalg.solve(z.T @ z + ridge * len(rows) / len(pick) * np.eye(z.shape[1]), z.T @ y)
        self.matrix, self.bias = (marks.T @ (root @ w[:-1])).astype(np.float32), w[-1].astype(np.float32)

    def predict(self, texts: list[str | None], batch: int = 128) -> tuple[list[str], list[float]]:
        known = [bool(t and LETTER.search(t)) and bool(self.langs) for t in texts]
        lang, score = ["und"] * len(texts), [0.0] * len(texts)
        rows = [i for i, k in enumerate(known) if k]
        for s in range(0, len(rows), batch):
            part = rows[s : s + batch]
            e = 4 * (presence([texts[i] for i in part], self.bits) @ self.matrix + self.bias)
            p = np.exp(e - e.max(1, keepdims=True))
            p /= p.sum(1, keepdims=True)
            for i, best, most in zip(part, p.argmax(1), p.max(1)):
                lang[i], score[i] = self.langs[best], float(min(1.0, most))
        return lang, score


def fit(docs: DataFrame, bound: int = BOUND, **options) -> Model:
    known = docs.where("text is not null and lang is not null and doc_id is not null").where(remainder_col("doc_id", 4) != 2)
    rows = sample_rows(known.select("doc_id", "text", "lang"), "doc_id", bound)
    return Model([(r["text"], r["lang"]) for r in rows if LETTER.search(r["text"])], **options)


def predict(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, held_out, lang_pred, score."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        def step(cols):
            lang, score = shared.value.predict(cols["text"])
            held = [i is not None and remainder(i, 4) == 2 for i in cols["doc_id"]]
            yield {"doc_id": cols["doc_id"], "held_out": held, "lang_pred": lang, "score": score}

        return step

    return map_columns(docs, ["doc_id", "text"], "doc_id long, held_out boolean, lang_pred string, score double", make)
