"""Near-duplicate detection by min-max hashing.

Each permutation of the shingle hashes gives two signature values, its minimum and its maximum, so half
the permutations are evaluated; minima and maxima agree between two sets with the probability of their
Jaccard similarity, and values of one permutation are close to independent. 50 bands of 5 values (125
permutations) miss a pair at similarity 0.75 with probability 1.4e-6. One byte of each signature value is
the sketch of a set, which rules out a pair 4.5 standard errors under the threshold.

Steps, none of which emits all pairs of a group:
1. One Arrow pass makes per document the set size, a 128-bit hash of its set, the band keys and the sketch.
2. Documents of equal sets form a class; only its smallest id goes on.
3. Band buckets of several members are kept, of buckets with equal members one.
4. Each round compares the members of a bucket to one hub and takes the hub out of the bucket. Sizes and
   sketches go first; texts are fetched for what they leave, each member's best link first and then those
   that still join two components. Buckets inside one component are done.
5. What two rounds leave is compared across components in blocks of bounded size, again by sketches first;
   texts go only to blocks, and to members in them, that sketches leave in doubt. A block gives only the
   links that join its members.
6. After each step the components are contracted by the new links: least labels with pointer jumping on
   tables written to the shared folder. Every link is confirmed on full sets of 64-bit shingle hashes.

Defined cases: null or wordless text has no shingles and is its own component; fewer than five words are
one shingle; ties take the smaller doc_id; rows that repeat a doc_id are one document, linked by the sets
of each of its rows; a null doc_id is linked with nothing; an empty table gives no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..session import ship
from .common import join_heavy, map_columns, materialize, maybe_among

SHINGLE, BANDS, ROWS, SEED = 5, 50, 5, 20240607
BLOCK, BLOCK_BYTES = 1024, 1 << 24  # members and bytes of shingles of a block
PERCENT = 75
ROUNDS = 2  # hubs tried in each bucket before components are compared across
_MIX = np.uint64(0x9E3779B97F4A7C15)
_STEP = np.uint64(0xD6E8FEB86659FD93)
SIGNATURES = "doc_id long, n_shingles long, h1 long, h2 long, bands array<long>, sketch binary"


class Shingler:
    """Sorted distinct 64-bit hashes of the five-word shingles of a text."""

    def __init__(self, width: int = SHINGLE, remembered: int = 200_000):
        self.width, self.remembered, self.known = width, remembered, {}

    def _hash(self, word: bytes) -> int:
        if len(self.known) >= self.remembered:
            self.known.clear()
        h = self.known[word] = xxhash.xxh64_intdigest(word)
        return h

    def __call__(self, text: str | None) -> np.ndarray:
        words = text.encode().lower().split() if text else []  # bytes: ASCII letters and white space only
        if not words:
            return np.empty(0, np.uint64)
        get, miss = self.known.get, self._hash
        w = np.array([get(x) or miss(x) for x in words], np.uint64)
        n, k = len(w), min(self.width, len(w))
        h = np.full(n - k + 1, k, np.uint64)
        for i in range(k):
            h = (h ^ w[i : n - k + 1 + i]) * _STEP
            h ^= h >> np.uint64(29)
        return np.unique(h * _MIX)


class Signer:
    """Band keys of a shingle set from minima and maxima of the permutations."""

    def __init__(self, bands: int = BANDS, rows: int = ROWS, seed: int = SEED):
        count = -(-bands * rows // 2)
        rng = np.random.default_rng(seed)
        self.odd = (rng.integers(0, 2**31, count, dtype=np.uint32) * np.uint32(2) + np.uint32(1))[:, None]
        self.flip = rng.integers(0, 2**32, count, dtype=np.uint32)[:, None]
        self.bands, self.rows = bands, rows
        self.salt = rng.integers(1, 2**63, bands, dtype=np.uint64)

    def values(self, shingles: np.ndarray) -> np.ndarray:
        low = (shingles >> np.uint64(32)).astype(np.uint32)
        least, most = [], []
        for s in range(0, len(low), 8192):
            x = (low[None, s : s + 8192] ^ self.flip) * self.odd
            least.append(x.min(1))
            most.append(x.max(1))
        return np.concatenate([np.min(least, 0), np.max(most, 0)])[: self.bands * self.rows]

    def keys(self, values: np.ndarray) -> list[int]:
        v = values.astype(np.uint64).reshape(self.bands, self.rows)
        key = self.salt.copy()
        for i in range(self.rows):
            key = (key ^ v[:, i]) * _STEP
            key ^= key >> np.uint64(31)
        return (key * _MIX).view(np.int64).tolist()


def sketch_of(values: np.ndarray) -> bytes:
    """One byte of each signature value."""
    return (values ^ (values >> np.uint32(16))).astype(np.uint8).tobytes()


def least_matches(size: int, percent: int) -> int:
    """Equal bytes of two sketches under which a pair is ruled out: 4.5 standard errors below the threshold."""
    j = percent / 100
    return int(size * max(0.0, j - 4.5 * (j * (1 - j) / size) ** 0.5))


def alike(mine: np.ndarray, theirs: np.ndarray, percent: int) -> bool:
    """Are two sorted distinct shingle sets similar enough?"""
    if not len(mine) or not len(theirs) or 100 * min(len(mine), len(theirs)) < percent * max(len(mine), len(theirs)):
        return False
    both = int(np.count_nonzero(mine[np.minimum(np.searchsorted(mine, theirs), len(mine) - 1)] == theirs))
    return 100 * both >= percent * (len(mine) + len(theirs) - both)


def signatures(docs: DataFrame, width: int = SHINGLE, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    def make():
        shingle, sign = Shingler(width), Signer(bands, rows)

        def step(cols):
            out: dict[str, list] = {"doc_id": cols["doc_id"], "n_shingles": [], "h1": [], "h2": [], "bands": [], "sketch": []}
            for text in cols["text"]:
                s = shingle(text)
                h = np.frombuffer(xxhash.xxh3_128_digest(s.tobytes()), np.int64)
                values = sign.values(s) if len(s) else None
                out["n_shingles"].append(len(s))
                out["h1"].append(int(h[0]))
                out["h2"].append(int(h[1]))
                out["bands"].append(sign.keys(values) if len(s) else [])
                out["sketch"].append(sketch_of(values) if len(s) else b"")
            yield out

        return step

    return map_columns(docs, ["doc_id", "text"], SIGNATURES, make)


def likely(pairs: DataFrame, marks: DataFrame, percent: int) -> DataFrame:
    """(a, b, score) of the pairs that sizes and sketches do not rule out; marks: id, n, sketch."""
    side = lambda x: marks.select(F.col("id").alias(x), F.col("n").alias(f"n{x}"), F.col("sketch").alias(f"s{x}"))
    fits = 100 * F.least("na", "nb") >= percent * F.greatest("na", "nb")
    both = pairs.join(side("b"), "b").join(side("a"), "a").where(fits).select("a", "b", "sa", "sb")

    def run(batches):
        for batch in batches:
            left, right = (np.frombuffer(b"".join(batch[c].to_pylist()), np.uint8).reshape(batch.num_rows, -1) for c in ("sa", "sb"))
            score = np.count_nonzero(left == right, 1) if batch.num_rows else np.empty(0, np.int64)
            keep = score >= least_matches(left.shape[1], percent) if batch.num_rows else np.empty(0, bool)
            yield pa.RecordBatch.from_arrays([batch["a"].filter(pa.array(keep)), batch["b"].filter(pa.array(keep)), pa.array(score[keep], pa.int64())], ["a", "b", "score"])

    ship(pairs.sparkSession)
    return both.mapInArrow(run, "a long, b long, score long")


def confirmed(pairs: DataFrame, texts: DataFrame, percent: int, width: int = SHINGLE) -> DataFrame:
    """(a, b) of the pairs whose full sets are similar enough; texts: id, text. Texts travel, as they are
    smaller than the hashes of their shingles."""
    side = lambda x: texts.select(F.col("id").alias(x), F.col("text").alias(f"t{x}"))
    both = pairs.select("a", "b").join(side("b"), "b").join(side("a"), "a")

    def make():
        shingle, last = Shingler(width), [None, None]

        def step(cols):
            out: dict[str, list] = {"a": [], "b": []}
            for a, b, ta, tb in zip(*(cols[c] for c in ("a", "b", "ta", "tb"))):
                if last[0] != ta:  # rows of one hub come together
                    last[:] = ta, shingle(ta)
                if alike(last[1], shingle(tb), percent):
                    out["a"].append(a)
                    out["b"].append(b)
            yield out

        return step

    return map_columns(both, ["a", "b", "ta", "tb"], "a long, b long", make)


def _in_bucket(members: DataFrame) -> DataFrame:
    """members (key, id, n, label, ...) dealt to the pairs of blocks (i, j) of their buckets, with all keys of each."""
    size = members.groupBy("key").agg(F.greatest(F.ceil(F.count("*") / BLOCK), F.ceil(F.sum("n") * 8 / BLOCK_BYTES)).cast("int").alias("blocks"))
    own = F.pmod(F.xxhash64("id", F.lit("block")), F.col("blocks")).cast("int")
    dealt = members.join(size, "key").withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    rest = [c for c in members.columns if c != "key"]
    return dealt.select("key", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", *rest)


def _first_common(keys: list[np.ndarray], x: int, y: int) -> int:
    return int(np.intersect1d(keys[x], keys[y], assume_unique=True)[0])


def _block(group: pa.Table, percent: int):
    """A function from a member's place to the places after it that sizes, labels and sketches leave, in the
    first bucket that both are in."""
    own, n = group["own"].to_numpy(), group["n"].to_numpy()
    sketch = np.frombuffer(b"".join(group["sketch"].to_pylist()), np.uint8).reshape(len(n), -1)
    keys = [np.array(k.as_py(), np.int64) for k in group["keys"]]
    least = least_matches(sketch.shape[1], percent)

    def partners(x: int, label: np.ndarray, bucket: int, same: bool) -> np.ndarray:
        rest = slice(x + 1, None)
        fits = (label[rest] != label[x]) & (100 * np.minimum(n[rest], n[x]) >= percent * np.maximum(n[rest], n[x]))
        if not same:
            fits &= own[rest] != own[x]
        y = np.flatnonzero(fits) + x + 1
        y = y[np.count_nonzero(sketch[y] == sketch[x], 1) >= least]
        return np.array([v for v in y if _first_common(keys, x, v) == bucket], np.int64)

    return partners


def in_doubt(members: DataFrame, percent: int) -> DataFrame:
    """(key, i, j, id): members with a partner in their block that the sketches do not rule out."""

    def look(key: tuple, group: pa.Table) -> pa.Table:
        bucket, i, j = (k.as_py() for k in key)
        ids, label = group["id"].to_numpy(), group["label"].to_numpy()
        partners, hit = _block(group, percent), np.zeros(group.num_rows, bool)
        for x in range(group.num_rows):
            y = partners(x, label, bucket, i == j)
            hit[x] |= len(y) > 0
            hit[y] = True
        found = np.unique(ids[hit])
        return pa.table({"key": pa.array([bucket] * len(found), pa.int64()), "i": pa.array([i] * len(found), pa.int32()), "j": pa.array([j] * len(found), pa.int32()), "id": pa.array(found, pa.int64())})

    ship(members.sparkSession)
    return _in_bucket(members).groupBy("key", "i", "j").applyInArrow(look, "key long, i int, j int, id long")


def across(members: DataFrame, texts: DataFrame, percent: int, width: int = SHINGLE) -> DataFrame:
    """Links (a, b) that join different labels within a bucket; members: key, id, n, label, sketch, keys.

    A bucket of more than BLOCK members, or BLOCK_BYTES of shingles, is dealt to blocks and each pair of
    blocks is one group. A pair that shares several buckets is made in the first of its common keys only.
    Sketches choose the members to look at, full sets decide, and a link whose ends the group has joined
    before is left out: a group gives fewer rows than it has members, however many pairs it holds.
    """
    doubt = materialize(in_doubt(members, percent))
    some = _in_bucket(members).join(doubt, ["key", "i", "j", "id"], "left_semi").join(texts, "id")

    def compare(key: tuple, group: pa.Table) -> pa.Table:
        bucket, i, j = (k.as_py() for k in key)
        ids, label = group["id"].to_numpy(), group["label"].to_numpy().copy()
        shingle = Shingler(width)
        sets = [shingle(t) for t in group["text"].to_pylist()]
        partners, a, b = _block(group, percent), [], []
        for x in range(len(ids)):
            for y in partners(x, label, bucket, i == j):
                if label[y] != label[x] and alike(sets[x], sets[y], percent):
                    label[label == label[y]] = label[x]
                    a.append(ids[x])
                    b.append(ids[y])
        a, b = np.array(a, np.int64), np.array(b, np.int64)
        return pa.table({"a": np.minimum(a, b), "b": np.maximum(a, b)})

    ship(members.sparkSession)
    return some.groupBy("key", "i", "j").applyInArrow(compare, "a long, b long")


def components(edges: DataFrame) -> DataFrame:
    """(id, label) with the least id reachable over edges (a, b); each round is a written table."""
    both = materialize(edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    labels = materialize(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("id"), F.least("a", "m").alias("label")))
    while True:
        near = (
            both.join(labels, both.b == labels.id)
            .groupBy("a")
            .agg(F.min("label").alias("near"))
            .join(labels, F.col("a") == labels.id)
            .select("id", F.col("label").alias("old"), F.least("label", "near").alias("mid"))
        )
        to = labels.select(F.col("id").alias("mid"), F.col("label").alias("jump"))
        new = materialize(near.join(to, "mid").select("id", "old", F.least("mid", "jump").alias("label")))
        labels = new.select("id", "label")
        if new.where("old <> label").isEmpty():
            return labels


def contracted(labels: DataFrame, links: DataFrame) -> DataFrame:
    """labels (id, label) after links (a, b) between ids: components of the labels that links join."""
    end = lambda x: labels.select(F.col("id").alias(x), F.col("label").alias(f"l{x}"))
    edges = links.join(end("a"), "a").join(end("b"), "b").where("la <> lb").select(F.least("la", "lb").alias("a"), F.greatest("la", "lb").alias("b"))
    edges = materialize(edges.distinct())
    if edges.isEmpty():
        return labels
    to = components(edges).select(F.col("id").alias("label"), F.col("label").alias("least"))
    return materialize(labels.join(to, "label", "left").select("id", F.coalesce("least", "label").alias("label")))


def apart(pairs: DataFrame, labels: DataFrame) -> DataFrame:
    """The pairs whose ends have different labels."""
    end = lambda x: labels.select(F.col("id").alias(x), F.col("label").alias(f"l{x}"))
    return pairs.join(end("b"), "b").join(end("a"), "a").where("la <> lb").drop("la", "lb")


def mixed(buckets: DataFrame, labels: DataFrame) -> DataFrame:
    """key, id, label of the buckets (key, id) that hold several labels; of buckets of equal members one."""
    now = buckets.join(labels, "id")
    mark = lambda salt: F.sum(F.shiftright(F.xxhash64("id", F.lit(salt)), 24))  # noqa: E731  sums of 40-bit hashes of the members
    kinds = now.groupBy("key").agg(F.min("label").alias("lo"), F.max("label").alias("hi"), F.count("*").alias("c"), *[mark(k).alias(f"m{k}") for k in range(3)])
    once = kinds.where("lo <> hi").groupBy("c", "m0", "m1", "m2").agg(F.min("key").alias("key"))
    return materialize(now.join(once.select("key"), "key", "left_semi").select("key", "id", "label"))


def link(docs: DataFrame, width: int = SHINGLE, bands: int = BANDS, rows: int = ROWS, percent: int = PERCENT, rounds: int = ROUNDS) -> DataFrame:
    """doc_id, n_shingles, class_id (least id of an equal set) and component_id, one row per document row."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    sign = materialize(signatures(docs, width, bands, rows))
    some = sign.where("n_shingles > 0 and doc_id is not null")
    total = some.count()
    classes = materialize(some.groupBy("h1", "h2").agg(F.min("doc_id").alias("class_id"), F.count("*").alias("rows")))
    copies = classes.where("rows > 1")
    owned = join_heavy(some.select("doc_id", "h1", "h2", "n_shingles", "bands", "sketch"), copies, ["h1", "h2"], "rows", total)
    heads = owned.where("class_id is null or doc_id = class_id").select(F.col("doc_id").alias("id"), F.col("n_shingles").alias("n"), "bands", "sketch")

    spread = heads.select("id", F.explode("bands").alias("key"))
    shared = spread.groupBy("key").agg(F.min("id").alias("lo"), F.max("id").alias("hi")).where("lo <> hi").select("key")
    found = materialize(spread.join(shared, "key").distinct())
    ids = materialize(found.select("id").distinct())
    labels = ids.select("id", F.col("id").alias("label"))
    marks = materialize(heads.join(ids, "id", "left_semi").select("id", "n", "sketch"))
    wanted = docs.where(maybe_among(ids)(F.col("doc_id"))).join(ids.select(F.col("id").alias("doc_id")), "doc_id", "left_semi")
    texts = materialize(wanted.select(F.col("doc_id").alias("id"), "text"))
    # rows of one id are one document: their classes are linked
    twice = some.groupBy("doc_id").agg(F.count("*").alias("times")).where("times > 1")
    if not twice.isEmpty():
        own = some.join(twice, "doc_id").join(classes, ["h1", "h2"]).select(F.col("doc_id"), "class_id")
        same = own.join(own.groupBy("doc_id").agg(F.min("class_id").alias("a")), "doc_id").select("a", F.col("class_id").alias("b")).where("a <> b").distinct()
        every = same.select(F.col("a").alias("id")).union(same.select(F.col("b").alias("id"))).union(ids).distinct()
        labels = contracted(materialize(every.select("id", F.col("id").alias("label"))), same)

    buckets = found
    for turn in range(rounds):
        buckets = mixed(buckets, labels)
        hub = buckets.groupBy("key").agg((F.min("id") if turn == 0 else F.max_by("id", F.xxhash64("id", F.lit(turn)))).alias("hub"))
        dealt = materialize(buckets.join(hub, "key").where("id <> hub"))  # one row of each member of a bucket, read three times
        pairs = apart(dealt.select(F.least("id", "hub").alias("a"), F.greatest("id", "hub").alias("b")).distinct(), labels)
        pairs = materialize(likely(pairs, marks, percent))
        best = pairs.groupBy("b").agg(F.max_by("a", F.struct("score", -F.col("a"))).alias("a"))
        labels = contracted(labels, confirmed(best, texts, percent, width))
        labels = contracted(labels, confirmed(apart(pairs, labels).join(best, ["a", "b"], "left_anti"), texts, percent, width))
        buckets = dealt.select("key", "id")
    left = mixed(buckets, labels)
    if not left.isEmpty():
        keys = left.groupBy("id").agg(F.sort_array(F.collect_set("key")).alias("keys"))
        labels = contracted(labels, across(left.join(marks, "id").join(keys, "id"), texts, percent, width))

    of_class = classes.join(labels.where("id <> label"), classes.class_id == labels.id, "left").select(
        "h1", "h2", "class_id", F.coalesce("label", "class_id").alias("component_id"), "rows"
    )
    changed = of_class.where("rows > 1 or component_id <> class_id")
    plain = F.col("doc_id").isNotNull() & (F.col("n_shingles") > 0)
    out = join_heavy(sign.select("doc_id", "n_shingles", "h1", "h2"), changed, ["h1", "h2"], "rows", total)
    return out.select("doc_id", "n_shingles", *[F.when(plain, F.coalesce(c, "doc_id")).otherwise(F.col("doc_id")).alias(c) for c in ("class_id", "component_id")])


def near_duplicates(docs: DataFrame, **options) -> DataFrame:
    """doc_id, n_shingles, component_id, kept."""
    return link(docs, **options).select(
        "doc_id", "n_shingles", "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)).alias("kept")
    )


def keep_one(docs: DataFrame, **options) -> DataFrame:
    """One document of each component, with all its columns; the rest goes.

    The ids that go are looked up, so a document that is linked with nothing never depends on a join key; a document
    that a Bloom filter of those ids doesn't hold is kept where it is, and only the rest is shuffled.
    A repeated id keeps one row, that with the least text (null first) and then the least other columns.
    """
    found = materialize(near_duplicates(docs, **options))
    gone = materialize(found.where("not kept").select("doc_id").distinct())
    maybe = maybe_among(gone)(F.col("doc_id").cast("long"))
    rest = docs.where(maybe).join(gone, "doc_id", "left_anti").select(*docs.columns)
    out = docs.where(~maybe).unionByName(rest)
    repeated = found.where("doc_id is not null").groupBy("doc_id").count().where("count > 1").select("doc_id")
    if repeated.isEmpty():
        return out
    place = "place"
    while place in docs.columns:
        place += "_"
    orderly = ["text", *(f.name for f in docs.schema if f.name not in ("text", "doc_id") and not isinstance(f.dataType, T.MapType))]
    first = F.row_number().over(Window.partitionBy("doc_id").orderBy(*orderly))
    many = out.join(repeated, "doc_id", "left_semi").withColumn(place, first).where(F.col(place) == 1)
    return out.join(repeated, "doc_id", "left_anti").select(*docs.columns).unionByName(many.select(*docs.columns))
