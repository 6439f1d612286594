"""Packing of token sequences by balanced attention cost.

A document's cost is linear in its tokens plus quadratic for attention. Documents longer than a sequence give whole
sequences first; what is left of each is taken in descending cost and given to the cheapest of all sequences with room. What fits
nowhere whole is cut to fill the room that is left, so nothing is padded: the last, smaller sequences of a batch have
lengths that are powers of two. A task packs what it reads, a few million tokens at a time: no shuffle, and the same
result when a lost task is run again.

Defined results: a null or empty text is its end id alone; repeated rows are packed one by one; null doc_id stays null;
an empty table gives an empty result; other columns are ignored, whatever their names; a very long text is held whole with
its ids, one at a time beside a batch of bounded size.
"""

from __future__ import annotations

import array
import heapq
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

CAPACITY = 2048
END = 1
#: Tokens packed together by a task.
BATCH_TOKENS = 1 << 21
#: Weight of the quadratic part of the cost, against 1 for each token.
ATTENTION = 1 / 1024

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"

#: White space in a row beyond which the faster library's splitting, which backtracks, might give up (it does at a million).
LONG_RUN = 10_000

#: Fixed value: how the byte-level vocabulary splits texts before merging.
PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""


def _letters() -> dict[str, int]:
    """The vocabulary file writes bytes as printable characters: those that print as they are, the others from 256 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    others = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(others)}


class Encoder:
    """Ids of texts as little-endian 32-bit numbers. The file's merges are carried out by the faster of two libraries, which
    gives the same ids for every code point; a text that holds one of the file's added tokens goes to the other one, and so
    does one with a run of white space that is too long for the first one's splitting."""

    def __init__(self, path: str):
        import json
        import re

        import tiktoken
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.long_run = re.compile(rf"\s{{{LONG_RUN}}}")
        self.added = tuple(t["content"] for t in spec["added_tokens"])
        letters = _letters()
        ranks = {bytes(letters[c] for c in token): i for token, i in spec["model"]["vocab"].items() if token not in self.added}
        self.fast = tiktoken.Encoding("merges", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})

    def one(self, text: str) -> bytes:
        if any(a in text for a in self.added) or (len(text) > LONG_RUN and self.long_run.search(text)):
            return array.array("I", self.tokenizer.encode(text, add_special_tokens=False).ids).tobytes()
        return self.fast.encode_to_numpy(text, disallowed_special=()).tobytes() if text else b""

    def __call__(self, texts: list[str]) -> list[bytes]:
        return [self.one(t) for t in texts]


_encoders: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    return _encoders[path]


def cost(tokens: int, attention: float = ATTENTION) -> float:
    return tokens + attention * tokens * tokens


class Rooms:
    """Sequences by the room they have left. A tree of minima over rooms gives the cheapest of all with at least so much."""

    NONE = (float("inf"), -1)

    def __init__(self, largest: int):
        self.width = 1 << largest.bit_length()
        self.heaps: dict[int, list[tuple[float, int]]] = {}
        self.least = [self.NONE] * (2 * self.width)

    def _refresh(self, room: int) -> None:
        i = room + self.width
        self.least[i] = self.heaps[room][0] if self.heaps[room] else self.NONE
        while i > 1:
            i >>= 1
            self.least[i] = min(self.least[2 * i], self.least[2 * i + 1])

    def put(self, room: int, spent: float, s: int) -> None:
        heapq.heappush(self.heaps.setdefault(room, []), (spent, s))
        self._refresh(room)

    def cheapest(self, room: int) -> tuple[float, int]:
        """(cost, sequence), of equal costs the first sequence; NONE if no sequence has that room."""
        i = room + self.width
        found = self.least[i]
        while i > 1:
            if not i & 1:
                found = min(found, self.least[i + 1])
            i >>= 1
        return found

    def take(self, room: int) -> None:
        """The cheapest sequence with exactly that room goes."""
        heapq.heappop(self.heaps[room])
        self._refresh(room)

    def rest(self) -> list[tuple[float, int]]:
        return [x for h in self.heaps.values() for x in h]


def pack(lengths: list[int], capacity: int = CAPACITY, attention: float = ATTENTION) -> list[tuple[int, int, int, int, int]]:
    """(document, start, length, sequence, offset) of all pieces; sequences are numbered from 0 and left without padding."""
    out: list[tuple[int, int, int, int, int]] = []
    number = 0
    tails: list[tuple[int, int, int]] = []
    for i, n in enumerate(lengths):
        whole = n // capacity
        for j in range(whole):
            out.append((i, j * capacity, capacity, number, 0))
            number += 1
        if n % capacity:
            tails.append((n % capacity, i, whole * capacity))
    total = sum(t[0] for t in tails)
    rooms = [capacity] * (total // capacity)
    rest = total % capacity
    rooms += [1 << k for k in range(rest.bit_length() - 1, -1, -1) if rest >> k & 1]
    size = list(rooms)
    open_rooms = Rooms(capacity)
    for s, room in enumerate(rooms):
        open_rooms.put(room, 0.0, s)
    tails.sort(key=lambda t: (-t[0], t[1]))
    homeless = []
    for n, i, start in tails:
        spent, s = open_rooms.cheapest(n)
        if s < 0:
            homeless.append((n, i, start))
            continue
        open_rooms.take(rooms[s])
        out.append((i, start, n, number + s, size[s] - rooms[s]))
        rooms[s] -= n
        if rooms[s]:
            open_rooms.put(rooms[s], spent + cost(n, attention), s)
    free = [s for _, s in sorted(open_rooms.rest(), reverse=True)]  # the cheapest is at the end
    for n, i, start in homeless:
        while n:
            s = free[-1]
            take = min(n, rooms[s])
            out.append((i, start, take, number + s, size[s] - rooms[s]))
            rooms[s] -= take
            n, start = n - take, start + take
            if not rooms[s]:
                free.pop()
    return out


def _packer(path: str, capacity: int, end: int, attention: float):
    def emit(ids: list[bytes], docs: list[int | None], base: int) -> tuple[pa.RecordBatch, int]:
        lengths = [len(x) // 4 for x in ids]
        pieces = pack(lengths, capacity, attention)
        columns = (
            pa.array([docs[p[0]] for p in pieces], pa.int64()), pa.array([p[1] for p in pieces], pa.int64()), pa.array([p[2] for p in pieces], pa.int64()),
            pa.array([common.crc(ids[p[0]][4 * p[1] : 4 * (p[1] + p[2])]) for p in pieces], pa.int64()), pa.array([lengths[p[0]] for p in pieces], pa.int64()),
            pa.array([base + p[3] for p in pieces], pa.int64()), pa.array([p[4] for p in pieces], pa.int64()),
        )
        return pa.RecordBatch.from_arrays(list(columns), ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]), base + 1 + max((p[3] for p in pieces), default=-1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, last = encoder(path), end.to_bytes(4, "little")
        base = TaskContext.get().partitionId() << 36
        ids: list[bytes] = []
        docs: list[int | None] = []
        held = 0
        for b in batches:
            for x, d in zip(encode(list(common.texts(b))), b.column("doc_id").to_pylist(), strict=True):
                ids.append(x + last)
                docs.append(d)
                held += len(x) // 4 + 1
                if held >= BATCH_TOKENS:
                    made, base = emit(ids, docs, base)
                    yield made
                    ids, docs, held = [], [], 0
        if ids:
            yield emit(ids, docs, base)[0]

    return run


def packed(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, end: int = END, attention: float = ATTENTION) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset."""
    common.ship(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), common.text_or_empty().alias("text")).mapInArrow(_packer(tokenizer, capacity, end, attention), PIECES)


def tokenizer_path(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))


def op9_packing(spark, sf_dir: str) -> DataFrame:
    """Pieces of all documents in sequences of 2048 tokens; defined results as in the module's docstring."""
    return packed(spark.read.parquet(f"{sf_dir}/documents.parquet"), tokenizer_path())
