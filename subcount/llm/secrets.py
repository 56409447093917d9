"""Secret scans: a linear-chain conditional random field over tokens, beside fixed patterns.

Tokens are runs of word characters (letters, digits, + / _ - and everything beyond ASCII) or of other
marks; lines are the sequences. States are begin, inside and outside of a secret. Each token's score sums
hashed weights of its shape, its own word, the two words before and the one after, their shapes, and the
file's density of digits and marks; transitions are learned with them by gradient ascent on the exact
likelihood (forward-backward over padded lines). Labels come from the fixed patterns on a bounded sample,
with the words inside a secret never used by name, so the model learns shapes and contexts and tags values
that the patterns miss.

Decoding is Viterbi. What a run of begin and inside states can win at most over staying outside is a sum
over its tokens; a token in no run with a positive bound is outside in every best path, so lines are cut
there and only the short rests are decoded, all at once. Features are computed as arrays over code points.

The sample: at most `bound` documents (1500), of their lines at most `lines` (3000) with a secret and, up to the
same number, as many others. A run of tagged tokens counts from `least` characters on (12): the labels are values
of 20 or 24 characters and assignments, and shorter runs that no fixed pattern names are mostly words and numbers.

Defined cases: null text is empty and has no spans; a model without any positive line adds nothing; spans
of the model that touch a fixed one are dropped; repeated rows give equal rows; further columns are
ignored (query) or kept (redaction).
"""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import give_back, map_columns, rewrite_batches, sample_rows

BOUND = 1500
# Fixed patterns of the base scan, with the least length of the match (of group 2 for assignments).
BASE = (
    ("assign", re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A), 6),
    ("access", re.compile(r"AKIA[A-Z0-9]+"), 20),
    ("hex", re.compile(r"[0-9a-f]{24,}"), 24),
)
KINDS = {"assign": 0, "access": 1, "hex": 2, "crf": 3}
SCHEMA = "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_crf long"
BEGIN, INSIDE, OUTSIDE = 0, 1, 2
BITS = 16
LEAST = 12  # characters of a run of tagged tokens
_A, _B = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)


def base_spans(text: str | None) -> list[tuple[str, int, int, int]]:
    """(kind, start, end, start of the value), by start and then kind."""
    out = []
    low = text.lower() if text else ""
    for kind, pattern, least in BASE if text else ():
        if kind == "assign" and not any(w in low for w in ("passw", "secret", "token", "api")):
            continue
        for m in pattern.finditer(text):
            at = m.start(2) if kind == "assign" else m.start()
            if m.end() - at >= least:
                out.append((kind, m.start(), m.end(), at))
    return sorted(out, key=lambda s: (s[1], KINDS[s[0]]))


def joined(spans) -> str:
    return ",".join(f"{k}:{s}:{e}" for k, s, e, *_ in sorted(spans, key=lambda s: (s[1], KINDS[s[0]])))


def _classes() -> np.ndarray:
    c = np.full(129, 4, np.uint8)  # other marks
    c[:33] = 0
    c[97:123], c[65:91], c[48:58], c[128] = 1, 2, 3, 5
    for x in "+/_-":
        c[ord(x)] = 6
    return c


CLASS = _classes()
BUCKET = np.repeat(np.arange(11), [1, 2, 2, 3, 1, 3, 4, 4, 4, 8, 9])  # of token lengths 0 to 40
_P = np.uint64(6364136223846793005)
_POWERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    size = 1 << max(12, n.bit_length())
    if size not in _POWERS:
        up, down = np.full(size, _P), np.full(size, np.uint64(pow(int(_P), -1, 1 << 64)))
        up[0] = down[0] = 1
        _POWERS.clear()
        _POWERS[size] = np.cumprod(up), np.cumprod(down)
    return _POWERS[size]


class Tokens:
    """Token bounds, lines and hashed features of some texts, laid out as one run of code points."""

    def __init__(self, texts: list[str]):
        whole = "\n".join(texts) + "\n"
        code = np.frombuffer(whole.encode("utf-32-le"), np.uint32)
        lens = np.fromiter(map(len, texts), np.int64, len(texts))
        self.offset = np.concatenate([[0], np.cumsum(lens + 1)])[:-1]
        kind = CLASS[np.minimum(code, 128)]
        group = np.where(kind == 0, 0, np.where(kind == 4, 2, 1)).astype(np.int8)
        edge = np.flatnonzero(np.diff(group, prepend=np.int8(0)))
        edge = np.append(edge, len(code))
        full = group[edge[:-1]] > 0
        self.start, self.end = edge[:-1][full], edge[1:][full]
        self.line = np.cumsum(code == 10)[self.start]
        begun = np.zeros(len(code) + 1, np.int32)
        begun[self.offset] = 1
        self.doc = np.cumsum(begun)[self.start] - 1
        self.word = group[self.start] == 1
        self._features(code, kind, lens)

    def _features(self, code, kind, lens):
        s, e, n = self.start, self.end, len(self.start)
        low = code + np.uint32(32) * (kind == 2)
        up, down = _powers(len(code) + 1)
        total = np.concatenate([[np.uint64(0)], np.cumsum((low.astype(np.uint64) + np.uint64(7)) * up[: len(code)])])
        word = (total[e] - total[s]) * down[s] * _A
        word ^= word >> np.uint64(31)
        held = np.bitwise_or.reduceat(np.uint8(1) << kind, s) if n else np.empty(0, np.uint8)
        is_digit = kind == 3
        digits = np.concatenate([[0], np.cumsum(is_digit, dtype=np.int32)])
        digit = digits[e] - digits[s]
        mixed = np.concatenate([[0], np.cumsum(is_digit[1:] != is_digit[:-1], dtype=np.int32), [0]])
        turns = np.maximum(mixed[e - 1] - mixed[s], 0)
        length = e - s
        bucket = BUCKET[np.minimum(length, 40)]
        shape = bucket + 11 * (((held >> 1) & 7) + 8 * (held >> 5).astype(np.int64)) + 352 * np.minimum(turns, 3)
        shape = (shape + 1408 * ~self.word).astype(np.uint64)
        named = np.where(length <= 16, word, shape * _B)  # long words count by shape only
        docs = len(lens)
        dense = np.bincount(self.doc, digit, docs)[self.doc] / np.maximum(1, lens[self.doc])
        marks = np.bincount(self.doc, ~self.word * length, docs)[self.doc] / np.maximum(1, lens[self.doc])
        file = (np.digitize(dense, [0.01, 0.05, 0.2]) + 4 * np.digitize(marks, [0.05, 0.15, 0.3])).astype(np.uint64)
        first = np.ones(n, bool)
        first[1:] = self.line[1:] != self.line[:-1]

        def shift(v, by):
            out = np.zeros_like(v)
            if by > 0:
                out[by:] = v[:-by]
                out[:by] = 0
            else:
                out[:by] = v[-by:]
            return out

        def within(v, by):
            x = shift(v, by)
            far = shift(self.line, by) != self.line
            x[far] = 1
            return x

        before, after = within(named, 1), within(named, -1)
        parts = [shape, within(shape, 1), within(shape, -1), before, after, within(named, 2), shape * _B ^ before, shape * _B ^ within(shape, 1), shape * _B ^ file, named]
        self.index = np.empty((len(parts), n), np.uint32)
        for k, p in enumerate(parts):
            h = (p + np.uint64(k + 1)) * _A
            h ^= h >> np.uint64(29)
            self.index[k] = ((h * _B) >> np.uint64(64 - BITS)).astype(np.uint32)
        self.first = first


class Field:
    """Weights (hashed features by state), transitions between states and starts."""

    def __init__(self):
        self.w = np.zeros((1 << BITS, 3), np.float32)
        self.t = np.zeros((3, 3))
        self.s = np.zeros(3)
        self.t[OUTSIDE, INSIDE] = self.s[INSIDE] = -6.0
        self.trained = False

    def emissions(self, index: np.ndarray) -> np.ndarray:
        e = self.w[index[0]].astype(np.float32)
        for row in index[1:]:
            e += self.w[row]
        return e

    def fit(self, sequences: list[tuple[np.ndarray, np.ndarray]], epochs: int = 6, batch: int = 128, rate: float = 0.3, decay: float = 1e-4, seed: int = 11):
        """sequences: (features x tokens indexes, labels). Adagrad on the log likelihood."""
        if not any((y != OUTSIDE).any() for _, y in sequences):
            return self
        rng, gw, gt, gs = np.random.default_rng(seed), np.full_like(self.w, 1e-2), np.full((3, 3), 1e-2), np.full(3, 1e-2)
        for _ in range(epochs):
            order = rng.permutation(len(sequences))
            for at in range(0, len(order), batch):
                part = [sequences[k] for k in order[at : at + batch]]
                longest = max(len(y) for _, y in part)
                mask = np.array([[t < len(y) for t in range(longest)] for _, y in part])
                e = np.zeros((len(part), longest, 3))
                gold = np.zeros_like(e)
                for b, (x, y) in enumerate(part):
                    e[b, : len(y)] = self.emissions(x)
                    gold[b, np.arange(len(y)), y] = 1
                marginal, pairs = self._expected(e, mask)
                d = (gold - marginal) * mask[..., None]
                gold_pairs = np.einsum("bti,btj->ij", gold[:, :-1], gold[:, 1:])
                dt, dsum = gold_pairs - pairs, d[:, 0].sum(0)
                flat = np.concatenate([x for x, _ in part], 1)
                rows = np.concatenate([d[b, : len(y)] for b, (_, y) in enumerate(part)])
                used, inverse = np.unique(flat, return_inverse=True)
                grad = np.stack([np.bincount(inverse.ravel(), np.tile(rows[:, k], len(flat)), len(used)) for k in range(3)], 1)
                grad -= decay * self.w[used] * len(part)
                gw[used] += grad**2
                self.w[used] += rate * grad / np.sqrt(gw[used])
                gt += dt**2
                self.t += 0.5 * rate * dt / np.sqrt(gt)
                gs += dsum**2
                self.s += 0.5 * rate * dsum / np.sqrt(gs)
        self.trained = True
        return self

    def _expected(self, e, mask):
        n, steps, _ = e.shape
        forward, backward = np.empty_like(e), np.zeros_like(e)
        forward[:, 0] = self.s + e[:, 0]
        for t in range(1, steps):
            f = np.logaddexp.reduce(forward[:, t - 1, :, None] + self.t, 1) + e[:, t]
            forward[:, t] = np.where(mask[:, t, None], f, forward[:, t - 1])
        z = np.logaddexp.reduce(forward[:, -1], 1)
        for t in range(steps - 2, -1, -1):
            b = np.logaddexp.reduce(self.t + (e[:, t + 1] + backward[:, t + 1])[:, None, :], 2)
            backward[:, t] = np.where(mask[:, t + 1, None], b, backward[:, t + 1])
        marginal = np.exp(forward + backward - z[:, None, None]) * mask[..., None]
        if steps == 1:
            return marginal, np.zeros((3, 3))
        both = forward[:, :-1, :, None] + self.t + (e[:, 1:] + backward[:, 1:])[:, :, None, :] - z[:, None, None, None]
        return marginal, (np.exp(np.minimum(both, 0)) * mask[:, 1:, None, None]).sum((0, 1))

    def viterbi(self, e: np.ndarray, first: np.ndarray) -> np.ndarray:
        """Best states of tokens with emissions e; first marks where a line begins."""
        n = len(e)
        states = np.full(n, OUTSIDE, np.int8)
        if not n or not self.trained:
            return states
        stay = self.t[OUTSIDE, OUTSIDE]
        enter = np.maximum(self.t.max(0) - stay, self.s - self.s[OUTSIDE])[:OUTSIDE]
        leave = max(0.0, (self.t[:OUTSIDE, OUTSIDE] - stay).max())
        won = np.cumsum((e[:, :OUTSIDE] + enter).max(1) - e[:, OUTSIDE], dtype=np.float64)
        low = np.minimum.accumulate(np.concatenate([[0.0], won[:-1]]))
        sure = np.maximum.accumulate(won[::-1])[::-1] - low + leave < 0
        open_ = np.flatnonzero(~sure)
        if not len(open_):
            return states
        begins = np.ones(len(open_), bool)
        begins[1:] = (np.diff(open_) > 1) | first[open_[1:]]
        at = np.flatnonzero(begins)
        size = np.diff(np.append(at, len(open_)))
        order = np.argsort(-size, kind="stable")
        at, size = open_[at[order]], size[order]
        head = np.where(first[at][:, None], self.s, self.t[OUTSIDE])  # a cut stands after a sure outside
        last = at + size
        closed = (last < n) & ~first[np.minimum(last, n - 1)]
        tail = np.where(closed[:, None], self.t[:, OUTSIDE], 0.0)
        steps, back = int(size[0]), []
        best = head + e[at]
        for t in range(1, steps):
            k = int(np.searchsorted(-size, -t, side="left"))  # segments longer than t
            x = best[:k, :, None] + self.t
            back.append(x.argmax(1).astype(np.int8))
            best[:k] = x.max(1) + e[at[:k] + t]
        state = (best + tail).argmax(1).astype(np.int8)
        states[last - 1] = state
        for t in range(steps - 1, 0, -1):
            k = len(back[t - 1])
            state[:k] = back[t - 1][np.arange(k), state[:k]]
            states[at[:k] + t - 1] = state[:k]
        return states


def fit(docs: DataFrame, bound: int = BOUND, lines: int = 3000, width: int = 64) -> Field:
    """A field from at most `bound` documents: their lines with secrets and a like number of others."""
    texts = [r["text"] for r in sample_rows(docs.select("doc_id", "text").where("text is not null"), "doc_id", bound)]
    return give_back(fit_texts(texts, lines, width))


def fit_texts(texts: list[str], lines: int = 3000, width: int = 64) -> Field:
    with_, without = [], []
    for text in texts:
        tokens = Tokens([text])
        if not len(tokens.start):
            continue
        y = np.full(len(tokens.start), OUTSIDE)
        for _, _, end, value in base_spans(text):
            inside = np.flatnonzero((tokens.start < end) & (tokens.end > value))
            y[inside] = INSIDE
            y[inside[:1]] = BEGIN
        cuts = np.flatnonzero(tokens.first)
        for a, b in zip(cuts, np.append(cuts[1:], len(y))):
            for s in range(a, b, width):
                part = slice(s, min(b, s + width))
                (with_ if (y[part] != OUTSIDE).any() else without).append((tokens.index[:, part], y[part]))
    keep = np.random.default_rng(5).permutation(len(without))[: max(lines - len(with_), len(with_))]
    return Field().fit(with_[:lines] + [without[k] for k in keep])


def scan_texts(texts: list[str | None], field: Field, chars: int = 1 << 17, least: int = LEAST) -> list[tuple[list, list]]:
    """(base spans, added spans) of each text; texts are laid out together up to about `chars` code points."""
    out: list[tuple[list, list]] = []
    group: list[str] = []

    def flush():
        tokens = Tokens(group)
        states = field.viterbi(field.emissions(tokens.index), tokens.first) if field.trained else np.empty(0)
        added: list[list] = [[] for _ in group]
        hit = np.flatnonzero(states != OUTSIDE)
        if len(hit):
            cut = np.ones(len(hit), bool)
            cut[1:] = (np.diff(hit) > 1) | (states[hit[1:]] == BEGIN) | tokens.first[hit[1:]]
            starts = hit[np.flatnonzero(cut)]
            ends = hit[np.append(np.flatnonzero(cut)[1:], len(hit)) - 1]
            for a, b in zip(starts, ends):
                d = tokens.doc[a]
                added[d].append(("crf", int(tokens.start[a] - tokens.offset[d]), int(tokens.end[b] - tokens.offset[d])))
        for text, more in zip(group, added):
            base = base_spans(text)
            more = [m for m in more if m[2] - m[1] >= least and not any(m[1] < e and s < m[2] for _, s, e, _ in base)]
            out.append((base, more))
        group.clear()

    size = 0
    for text in texts:
        group.append(text or "")
        size += len(group[-1])
        if size >= chars:
            flush()
            size = 0
    if group:
        flush()
    return out


def scan(docs: DataFrame, field: Field, least: int = LEAST) -> DataFrame:
    """doc_id, counts of the base spans by kind, digest of those, all spans, and the number of added ones."""
    shared = docs.sparkSession.sparkContext.broadcast(field)

    def make():
        def step(cols):
            out: dict[str, list] = {k: [] for k in ("doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_crf")}
            for doc_id, (base, more) in zip(cols["doc_id"], scan_texts(cols["text"], shared.value, least=least)):
                kinds = [k for k, *_ in base]
                row = (doc_id, *(kinds.count(k) for k in ("assign", "access", "hex")), hashlib.sha256(joined(base).encode()).hexdigest(), joined([*base, *more]), len(more))
                for name, value in zip(out, row):
                    out[name].append(value)
            yield out

        return step

    return map_columns(docs, ["doc_id", "text"], SCHEMA, make)


def redacted(text: str, base, more, mark: str = "[SECRET]") -> str:
    """The text with each secret value replaced; the name of an assignment stays."""
    spans = sorted([(v, e) for _, _, e, v in base] + [(s, e) for _, s, e in more])
    parts, at = [], 0
    for s, e in spans:
        if s >= at:
            parts += [text[at:s], mark]
        at = max(at, e)
    return "".join([*parts, text[at:]])


def redact(docs: DataFrame, field: Field, mark: str = "[SECRET]", least: int = LEAST) -> DataFrame:
    """The same rows and columns with secrets masked in text."""
    shared = docs.sparkSession.sparkContext.broadcast(field)

    def make():
        def step(batch):
            at = batch.schema.get_field_index("text")
            texts = batch.column(at).to_pylist()
            found = scan_texts(texts, shared.value, least=least)
            new = [t if t is None or not (b or m) else redacted(t, b, m, mark) for t, (b, m) in zip(texts, found)]
            return batch.set_column(at, batch.schema.field(at), pa.array(new, batch.schema.field(at).type))

        return step

    return rewrite_batches(docs, make)
