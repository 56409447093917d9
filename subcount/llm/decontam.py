"""Benchmark decontamination: Wu-Manber multi-pattern search over words.

Words are the symbols. A pattern is a window of 13 consecutive item words (a shorter item is one window).
For patterns of one length m, a table of two-word blocks says how far a position may jump because no
pattern can end there; only blocks that end some pattern (jump 0) look into a bucket keyed by the block,
and a candidate is confirmed by comparing all its words. Words outside the benchmark share one code that
is in no block, so most positions jump m - 1 words at once.

The patterns go to the tasks as one broadcast. Its size is checked: a benchmark beyond `max_words` is
cut into chunks of items and the documents are searched once per chunk, with the hits carried along as a
column, so nothing is shuffled and what is broadcast stays bounded.

Defined cases: null or wordless text has no words and is not contaminated; null or wordless items have no
windows; an empty benchmark contaminates nothing; equal windows of several items count for each item;
repeated rows are judged each by itself; further columns are ignored (query) or kept (filter).
"""

from __future__ import annotations

import hashlib
import re
import string
from collections import defaultdict

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_columns, rewrite_batches

WINDOW = 13
WORDS = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
LOWER = str.maketrans(string.ascii_uppercase, string.ascii_lowercase)
MAX_WORDS = 2_000_000


def words_of(text: str | None) -> list[str]:
    return WORDS.findall(text.translate(LOWER)) if text else []


class Patterns:
    """Windows of items and their shift tables, one table for each pattern length that occurs."""

    def __init__(self, items: list[tuple[object, str | None]], window: int = WINDOW):
        self.code: dict[str, int] = {}
        owners: dict[tuple[int, ...], set] = defaultdict(set)
        for item_id, text in items:
            ids = [self.code.setdefault(w, len(self.code)) for w in words_of(text)]
            for k in range(max(1, len(ids) - window + 1) if ids else 0):
                owners[tuple(ids[k : k + window])].add(item_id)
        self.owners = dict(owners)
        self.tables = []
        for m in sorted({len(p) for p in owners}, reverse=True):
            block = min(2, m)
            jumps: dict[tuple[int, ...], int] = {}
            buckets: dict[tuple[int, ...], list] = defaultdict(list)
            for p in (p for p in owners if len(p) == m):
                for end in range(block, m + 1):
                    key = p[end - block : end]
                    jumps[key] = min(jumps.get(key, m), m - end)
                buckets[p[m - block :]].append(p)
            self.tables.append((m, block, jumps, dict(buckets)))

    def search(self, words: list[str]) -> tuple[list[tuple[int, int]], set]:
        """Merged [start, end) spans of hit words and the items with an occurring window."""
        get, unknown = self.code.get, -1
        ids = [get(w, unknown) for w in words]
        n, found, items = len(ids), [], set()
        for m, block, jumps, buckets in self.tables:
            far, jump, at = m - block + 1, jumps.get, m
            while at <= n:
                key = tuple(ids[at - block : at])
                by = jump(key, far)
                if by:
                    at += by
                    continue
                start = at - m
                for p in buckets[key]:
                    if p[0] == ids[start] and p == tuple(ids[start:at]):
                        found.append((start, at))
                        items |= self.owners[p]
                        break  # equal windows are one pattern
                at += 1
        return merged(found), items


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for start, end in sorted(spans):
        if out and start <= out[-1][1]:
            out[-1] = (out[-1][0], max(end, out[-1][1]))
        else:
            out.append((start, end))
    return out


def chunks_of(benchmark: DataFrame, max_words: int) -> int:
    """Into how many chunks of about max_words words the items are dealt."""
    total = benchmark.where("text is not null").agg(F.sum(F.length("text"))).first()[0] or 0
    return max(1, -(-total // (max_words * 4)))


def chunk_patterns(benchmark: DataFrame, parts: int, k: int, window: int):
    """The patterns of chunk k as a broadcast; the driver holds the items of one chunk at a time."""
    sized = benchmark.select("item_id", "text").where("text is not null")
    items = sized if parts == 1 else sized.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(parts)) == k)
    return benchmark.sparkSession.sparkContext.broadcast(Patterns([tuple(r) for r in items.collect()], window))


def find(
    docs: DataFrame,
    benchmark: DataFrame,
    window: int = WINDOW,
    max_words: int = MAX_WORDS,
    id_col: str = "doc_id",
    text_col: str = "text",
) -> DataFrame:
    """Per document: n_words, merged hit spans (in words) and the ids (as text) of items with hits."""
    schema = "doc_id long, n_words long, spans array<struct<s:long,e:long>>, items array<string>"
    out = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    parts = chunks_of(benchmark, max_words)
    for k in range(parts):
        patterns = chunk_patterns(benchmark, parts, k, window)
        last, first = k == parts - 1, k == 0

        def make(patterns=patterns, first=first, last=last):
            def step(cols):
                cols = cols | ({} if first else {"before": list(zip(cols["spans"], cols["items"]))})
                res: dict[str, list] = {"doc_id": cols["doc_id"], "n_words": [], "spans": [], "items": []}
                for i, text in enumerate(cols["text"]):
                    words = words_of(text)
                    spans, items = patterns.value.search(words)
                    items = {str(x) for x in items}
                    if not first:
                        old, old_items = cols["before"][i]
                        spans = merged([*spans, *((x["s"], x["e"]) for x in old)])
                        items |= set(old_items)
                    res["n_words"].append(len(words))
                    res["spans"].append([{"s": s, "e": e} for s, e in spans])
                    res["items"].append(sorted(items))
                yield res if last else res | {"text": cols["text"]}

            return step

        names = ["doc_id", "text"] + ([] if first else ["spans", "items"])
        out = map_columns(out, names, schema + ("" if last else ", text string"), make)
    return out


def contamination(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """find() with the contract's digest and verdict: hit words are a twentieth of all words or more."""
    hit = F.aggregate("spans", F.lit(0).cast("long"), lambda a, x: a + x["e"] - x["s"])
    return find(docs, benchmark, **options).select(
        "doc_id",
        "n_words",
        hit.alias("n_hit"),
        F.size("items").cast("long").alias("n_items"),
        F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("items_sha256"),
        ((hit > 0) & (20 * hit >= F.col("n_words"))).alias("contaminated"),
    )


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, max_words: int = MAX_WORDS) -> DataFrame:
    """The documents that are not contaminated, with all their columns; one pass per benchmark chunk.

    With more than one chunk the hit spans so far go along as a column of the row, and the last pass filters
    on all of them, so each row is judged by itself whatever its id.
    """
    parts = chunks_of(benchmark, max_words)
    spans = "spans"
    while spans in docs.columns:
        spans += "_"
    out = docs
    if parts > 1:
        out = docs.withColumn(spans, F.lit(None).cast("array<struct<s:long,e:long>>"))
    for k in range(parts):
        patterns = chunk_patterns(benchmark, parts, k, window)

        def make(patterns=patterns, first=k == 0, last=k == parts - 1):
            def step(batch: pa.RecordBatch) -> pa.RecordBatch:
                texts = batch.column(batch.schema.get_field_index("text")).to_pylist()
                at = batch.schema.get_field_index(spans)
                before = [None] * len(texts) if first else batch.column(at).to_pylist()
                keep, found = [], []
                for text, old in zip(texts, before):
                    words = words_of(text)
                    now = patterns.value.search(words)[0]
                    if old:
                        now = merged([*now, *((x["s"], x["e"]) for x in old)])
                    hit = sum(e - s for s, e in now)
                    keep.append(not (hit and 20 * hit >= len(words)))
                    found.append([{"s": s, "e": e} for s, e in now])
                if last:
                    return batch.filter(pa.array(keep, pa.bool_()))
                field = batch.schema.field(at)
                return batch.set_column(at, field, pa.array(found, field.type))

            return step

        out = rewrite_batches(out, make)
    return out.drop(spans) if parts > 1 else out
