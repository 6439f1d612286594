"""Merge-type subword encoding by a prefix table, and decoding.

Merging always ends in the same tokens, so every prefix of a text has one last token. It is found from left to right:
an automaton lists the tokens that end at a place, and the one that may follow the last token before it is stored. Two
tokens may follow each other when merging their joined text gives just the two. The ids are read off backwards.

No token holds a space mark after another character, so words, with the run of spaces before them, are encoded apart and
remembered up to a bound.

Defined results: a null text is an empty one, whose only id is the end id; repeated rows give repeated results; an empty
table gives an empty result; other columns are ignored, whatever their names. Very long texts, words and runs of spaces take
time in proportion to their length.
"""

from __future__ import annotations

import hashlib
import heapq
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

SPACE = "▁"
_RUNS = re.compile(f"{SPACE}+[^{SPACE}]*")


class Codec:
    """Encodes and decodes as the library does for a merge-type model with byte fallback and without normalisation."""

    def __init__(self, path: str):
        import ahocorasick
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        size = model.get_piece_size()
        self.end = model.eos_id()
        self.score: dict[str, float] = {}
        self.ids: dict[str, int] = {}
        self.byte_ids: dict[int, int] = {}
        self.out: list[bytes] = []
        for i in range(size):
            piece = model.id_to_piece(i)
            special = model.is_control(i) or model.is_unknown(i) or model.is_unused(i)
            if model.is_byte(i):
                self.byte_ids[int(piece[3:5], 16)] = i
                self.out.append(bytes([int(piece[3:5], 16)]))
            elif special:
                self.out.append(b"")
            else:
                self.score[piece], self.ids[piece] = model.get_score(i), i
                self.out.append(piece.replace(SPACE, " ").encode())
        if any(SPACE in p.lstrip(SPACE) for p in self.ids):
            raise ValueError("tokens that cross words are not supported")
        self.longest = max(map(len, self.ids), default=1)
        self.tokens = ahocorasick.Automaton()
        for p in self.ids:
            if len(p) == 1 or self.merged(p) == [p]:  # others never result from merging
                self.tokens.add_word(p, p)
        self.tokens.make_automaton()
        self.may_follow: dict[tuple[str, str], bool] = {}
        self.written = {p: str(i) for p, i in self.ids.items()}
        self.text = {p: self.out[i].decode().replace(" ", SPACE) for p, i in self.ids.items()}
        self.unlike: dict[str, str] = {}
        self.words = Words(self.word, common.CACHE_ENTRIES * 3 // 4)

    def merged(self, text: str) -> list[str]:
        """Merging carried out: the best-scored neighbours first, the leftmost of equals."""
        part = list(text)
        after = list(range(1, len(part) + 1))
        before = list(range(-1, len(part) - 1))
        heap: list[tuple[float, int, int, str]] = []

        def offer(i: int, j: int) -> None:
            if 0 <= i and j < len(part) and (s := self.score.get(t := part[i] + part[j])) is not None:
                heapq.heappush(heap, (-s, i, j, t))

        for i in range(len(part) - 1):
            offer(i, i + 1)
        while heap:
            _, i, j, t = heapq.heappop(heap)
            if not part[i] or not part[j] or part[i] + part[j] != t or after[i] != j:
                continue
            part[i], part[j] = t, ""
            after[i] = after[j]
            if after[j] < len(part):
                before[after[j]] = i
            offer(before[i], i)
            offer(i, after[i])
        return [p for p in part if p]

    def follows(self, a: str, b: str) -> bool:
        """May token b stand after token a?"""
        known = self.may_follow.get((a, b))
        if known is None:
            if len(self.may_follow) > 2_000_000:
                self.may_follow.clear()
            # a character outside the vocabulary joins nothing
            known = self.may_follow[a, b] = a not in self.ids or b not in self.ids or self.merged(a + b) == [a, b]
        return known

    def tokens_of(self, word: str) -> list[str]:
        """Prefix table of one word, read backwards. The automaton lists tokens by their end, so the last token of every
        shorter prefix is known; a prefix that no token ends holds a character outside the vocabulary there."""
        last: list[str | None] = [None] * (len(word) + 1)
        may = self.may_follow
        for end, token in self.tokens.iter(word):
            end += 1
            if last[end] is None:
                start = end - len(token)
                if start:
                    before = last[start]
                    if before is None:
                        last[start] = word[start - 1]
                    else:
                        fits = may.get((before, token))
                        if not (self.follows(before, token) if fits is None else fits):
                            continue
                last[end] = token
        out, at = [], len(word)
        while at:
            token = last[at] or word[at - 1]
            out.append(token)
            at -= len(token)
        out.reverse()
        return out

    def word(self, word: str) -> str:
        """Ids, joined by spaces, of a word with its leading space marks. What they decode to is compared with the word; a
        difference (there is none where every character has an id or bytes) is kept for decoding."""
        tokens = self.tokens_of(word)
        decoded = "".join([self.text.get(t) or self.decoded(t) for t in tokens])
        if decoded != word:
            self.unlike[word] = decoded.replace(SPACE, " ")
        return " ".join([self.written.get(t) or self.in_bytes(t) for t in tokens])

    def in_bytes(self, char: str) -> str:
        return " ".join([str(self.byte_ids[x]) for x in char.encode("utf-8", "surrogatepass")])

    def decoded(self, char: str) -> str:
        """A character outside the vocabulary, by way of its byte ids."""
        return b"".join([self.out[int(i)] for i in self.in_bytes(char).split(" ")]).decode("utf-8", "replace")

    def encode(self, text: str) -> tuple[str, int, str]:
        """(decimal ids joined by spaces with the end id, their number, the text that the ids decode to)."""
        if not text:
            return str(self.end), 1, ""
        marked = SPACE + text.replace(" ", SPACE)
        words = _RUNS.findall(marked) if SPACE * 2 in marked else [SPACE + w for w in marked[1:].split(SPACE)]
        ids = " ".join(map(self.words.__getitem__, words))
        if self.unlike:
            decoded = "".join([self.unlike.get(w) or w.replace(SPACE, " ") for w in words])
        else:
            decoded = marked.replace(SPACE, " ")
        return f"{ids} {self.end}", ids.count(" ") + 2, decoded[1:]


class Words(dict):
    """Ids of words, remembered in two generations: a full one becomes the old one, and what is used of it moves on."""

    def __init__(self, make, size: int):
        super().__init__()
        self.make, self.size, self.old = make, size, {}

    def __missing__(self, word: str) -> str:
        if len(self) >= self.size:
            self.old = dict(self)
            self.clear()
        known = self.old.get(word)
        if known is None:
            known = self.make(word)
        self[word] = known
        return known


_codecs: dict[str, Codec] = {}


def codec(path: str) -> Codec:
    if path not in _codecs:
        _codecs[path] = Codec(path)
    return _codecs[path]


def _coder(path: str, texts_too: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path)
        for b in batches:
            n, ids_sha, text_sha, ids_out, text_out = [], [], [], [], []
            for t in common.texts(b):
                ids, count, decoded = c.encode(t)
                n.append(count)
                ids_sha.append(hashlib.sha256(ids.encode()).hexdigest())
                text_sha.append(hashlib.sha256(decoded.encode()).hexdigest())
                if texts_too:
                    ids_out.append([int(x) for x in ids.split(" ")])
                    text_out.append(decoded)
            columns = [b.column("doc_id"), pa.array(n, pa.int64()), pa.array(ids_sha, pa.string()), pa.array(text_sha, pa.string())]
            names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
            if texts_too:
                columns += [pa.array(ids_out, pa.list_(pa.int32())), pa.array(text_out, pa.string())]
                names += ["ids", "decoded"]
            yield pa.RecordBatch.from_arrays(columns, names)

    return run


def coded(docs: DataFrame, model: str, texts: bool = True) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 and, with texts, ids and decoded: a row per row of docs, no shuffle."""
    common.ship(docs.sparkSession)
    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>, decoded string" * texts
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), common.text_or_empty().alias("text")).mapInArrow(_coder(model, texts), schema)


def model_path(name: str = "piece_bpe_32k.model") -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))


def op4_sentencepiece(spark, sf_dir: str) -> DataFrame:
    """Ids and decoded text of every document, as digests; defined results as in the module's docstring."""
    return coded(spark.read.parquet(f"{sf_dir}/documents.parquet"), model_path(), texts=False)
