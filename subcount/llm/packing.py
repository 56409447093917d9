"""Best-fit packing: bounded-space online best fit of token pieces into fixed-length sequences.

A fixed number of bins stays open. Their free space is kept in one integer used as a bitset: bit f is set
while some open bin has f tokens free, so the tightest bin that fits is the lowest set bit from the
piece's length on. When no bin fits and all are open, the fullest is closed first.

Each task packs what it scans, with memory bounded by the open bins, and needs no shuffle; only the bins
open at the end of a task stay part-filled. Sequence numbers carry the task's number, so a retried task
writes the same rows.

Defined cases: null text is empty text (one piece: the end id alone); an empty table gives no rows;
repeated rows and repeated or null ids are packed as they come; further columns are ignored.
"""

from __future__ import annotations

import base64
import json
import re
import zlib
from array import array
from collections import deque
from functools import cached_property, lru_cache

from pyspark import TaskContext
from pyspark.sql import DataFrame

from .common import map_columns

CAPACITY, OPEN_BINS, END_ID = 2048, 1024, 0
SCHEMA = "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long"


class OpenBins:
    """Open bins by free space. place(n) returns (bin number, offset) of a piece of n tokens."""

    def __init__(self, capacity: int = CAPACITY, bins: int = OPEN_BINS):
        self.capacity, self.bins = capacity, bins
        self.open = self.next = 0
        self.free = 0
        self.by_free: dict[int, deque[int]] = {}

    def _take(self, room: int) -> int:
        queue = self.by_free[room]
        number = queue.popleft()
        if not queue:
            self.free &= ~(1 << room)
        self.open -= 1
        return number

    def place(self, n: int) -> tuple[int, int]:
        if not 0 < n <= self.capacity:
            raise ValueError(f"a piece has 1 to {self.capacity} tokens, not {n}")
        fits = self.free >> n
        if fits:
            room = n + (fits & -fits).bit_length() - 1
            number = self._take(room)
        else:
            number, room = self.next, self.capacity
            self.next += 1
        left = room - n
        if left:
            if self.open == self.bins:
                self._take((self.free & -self.free).bit_length() - 1)
            self.by_free.setdefault(left, deque()).append(number)
            self.free |= 1 << left
            self.open += 1
        return number, self.capacity - room


def cut_points(n: int, capacity: int = CAPACITY) -> list[tuple[int, int]]:
    """(start, length) of a document's pieces: whole if it fits, else full pieces after a shorter first."""
    first = n % capacity or min(n, capacity)
    return [(0, first), *((s, capacity) for s in range(first, n, capacity))]


class Tokens:
    """Ids of the given byte-level vocabulary, as `tokenizers` gives them.

    The rank file of the same vocabulary is encoded about six times faster; the two agree on every code point
    (tested). Texts that hold a special token's string go to `tokenizers`.
    """

    def __init__(self, json_path: str, ranks_path: str | None, pattern: str | None):
        with open(json_path, encoding="utf-8") as described:
            special = [t["content"] for t in json.load(described)["added_tokens"]]
        self.json_path, self.fast = json_path, None
        if ranks_path:
            import tiktoken

            with open(ranks_path, "rb") as lines:
                ranks = {base64.b64decode(k): int(v) for k, v in map(bytes.split, lines)}
            self.fast = tiktoken.Encoding("given", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
        self.odd = re.compile("|".join(map(re.escape, special)) or "(?!)").search

    @cached_property
    def slow(self):
        """`tokenizers` itself, loaded when a text needs it."""
        from tokenizers import Tokenizer

        return Tokenizer.from_file(self.json_path)

    def __call__(self, text: str) -> list[int]:
        if self.fast is None or self.odd(text):
            return self.slow.encode(text, add_special_tokens=False).ids
        return self.fast.encode_ordinary(text)


@lru_cache(maxsize=2)
def tokens(json_path: str, ranks_path: str | None, pattern: str | None) -> Tokens:
    return Tokens(json_path, ranks_path, pattern)


def public_vocabulary() -> tuple[str, str, str]:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN


def pack(
    docs: DataFrame,
    vocabulary: tuple[str, str | None, str | None] | None = None,
    capacity: int = CAPACITY,
    bins: int = OPEN_BINS,
    end_id: int = END_ID,
    with_ids: bool = False,
    id_col: str = "doc_id",
    text_col: str = "text",
) -> DataFrame:
    """One row per piece of each document; with_ids adds the token ids of the piece. A vocabulary that is given
    is read by each worker at that path."""

    def make():
        # the path of the public vocabulary is that of the worker, which may differ from the driver's
        encode, open_bins = tokens(*(vocabulary or public_vocabulary())), OpenBins(capacity, bins)
        base = TaskContext.get().partitionId() << 40

        def step(cols):
            names = ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset", "ids"]
            out: dict[str, list] = {n: [] for n in names}
            for doc_id, text in zip(cols[id_col], cols[text_col]):
                ids = encode(text) if text else []
                ids.append(end_id)
                for k, (start, n) in enumerate(cut_points(len(ids), capacity)):
                    part = array("I", ids[start : start + n])
                    number, offset = open_bins.place(n)
                    for name, value in zip(names, (doc_id, k, start, n, zlib.crc32(part), base + number, offset)):
                        out[name].append(value)
                    if with_ids:
                        out["ids"].append(part.tolist())
            if not with_ids:
                del out["ids"]
            yield out

        return step

    return map_columns(docs, [id_col, text_col], SCHEMA + ", ids array<long>" * with_ids, make)
