"""Byte-level BPE encoding over a trie of words, and decoding.

The merges of a word are never replayed. What makes this possible is a property of BPE: the
encoding of a prefix is the encoding of a shorter prefix and one last token, and that token is the
only one that ends the prefix and sits stably after the last token of what is before it. Distinct
words go into a trie; each node holds the last token of its prefix and where that token begins,
found from the states of the nodes above it, so a prefix that many words share is worked out once.

A pair of tokens is stable if no merge across its seam would have come before the merges that
built its two sides; taking these merges back, latest first, shows it.

Results: a null text is the empty text with no ids; equal rows give equal rows; an id beyond the
vocabulary raises on decoding; bytes that are not UTF-8 decode to U+FFFD. Word caches are bounded
by ``max_words`` and start again when full; a text of any length is encoded whole, by one task; an
empty table gives an empty table; the column that is added takes the place of one with its name.
"""

from __future__ import annotations

import json
import re
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import list_array, ragged, released, slices, table

#: Fixed value: how the byte-level vocabulary splits text before any merge.
WORD = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+")
#: White space other than the space and the line feed, and where a text may be cut apart.
EDGES = frozenset(chr(c) for c in range(0x3001) if chr(c).isspace()) - {" ", "\n"}
BETWEEN = re.compile(r"(?<=\S) (?=\S)")
#: ASCII characters that are no letters, numbers, spaces or apostrophes: side by side they are one word.
MARKS = "".join(chr(c) for c in range(33, 127) if not chr(c).isalnum() and c != 39)
#: Beyond these characters, Unicode tables of different ages disagree on letters and numbers; the
#: tokenizer's own splitter is asked there.
YOUNG = re.compile("[԰-‏‿-\U0010ffff]")


def vocabulary_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def printable_bytes() -> dict[str, int]:
    """The vocabulary file writes bytes as characters: printable Latin-1 bytes stand for themselves,
    the others follow from U+0100."""
    own = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174]
    rest = [b for b in range(256) if b not in set(own)]
    return {chr(b): b for b in own} | {chr(256 + i): b for i, b in enumerate(rest)}


class Recent:
    """What was worked out lately, in two generations of at most ``size`` entries and one batch."""

    def __init__(self, size: int):
        self.size, self.new, self.old = size, {}, {}

    def forget(self) -> None:
        self.new, self.old = {}, {}

    def lacking(self, keys: set[str]) -> list[str]:
        """The keys that have to be worked out; all others are in ``new`` from now on."""
        if len(self.new) > self.size:
            self.old, self.new = self.new, {}
        new, old = self.new, self.old
        absent = []
        for k in keys:
            if k not in new:
                if (v := old.get(k)) is None:
                    absent.append(k)
                else:
                    new[k] = v
        return absent


class Trie:
    """Encoder and decoder of one vocabulary. Inside, a byte is its own number and merge r is 256+r."""

    def __init__(self, path: str, max_words: int = 60_000):
        spec = json.load(open(path, encoding="utf-8"))
        by_char, vocab = printable_bytes(), spec["model"]["vocab"]
        raw = lambda s: bytes(by_char[c] for c in s)
        merges = [m.split(" ") if isinstance(m, str) else m for m in spec["model"]["merges"]]
        pieces = [bytes([b]) for b in range(256)] + [raw(a + b) for a, b in merges]
        self.number = {p: i for i, p in enumerate(pieces)}
        if len(self.number) != len(pieces):
            raise ValueError("two merges of the vocabulary make the same token")
        self.left, self.right = [0] * 256, [0] * 256
        self.joined: dict[int, int] = {}
        for i, (a, b) in enumerate(merges):
            x, y = self.number[raw(a)], self.number[raw(b)]
            self.left.append(x)
            self.right.append(y)
            self.joined[x << 20 | y] = 256 + i
        by_piece = {raw(s): i for s, i in vocab.items()}
        self.out = [int(by_piece[p]).to_bytes(4, "little") for p in pieces]
        self.special = {t["content"]: int(t["id"]) for t in spec.get("added_tokens", ())}
        self.split_special = re.compile("|".join(re.escape(s) for s in sorted(self.special, key=len, reverse=True)) or r"(?!)")
        self._automaton(pieces)
        self.own_splitter = None
        self.path = path
        self.chunks, self.words, self.stable = Recent(max_words), Recent(max_words), {}
        size = max([*by_piece.values(), *self.special.values()]) + 1
        table = [b""] * size
        for p, i in by_piece.items():
            table[i] = p
        for s, i in self.special.items():
            table[i] = s.encode()
        self.lengths = np.array([len(p) for p in table], np.int64)
        self.starts = np.cumsum(self.lengths) - self.lengths
        self.bytes = np.frombuffer(b"".join(table), np.uint8)

    def forget(self) -> None:
        """Lets go of words: workers outlive their tasks, and other stages need the memory."""
        for held in (self.chunks, self.words):
            held.forget()
        self.stable.clear()

    def is_stable(self, a: int, b: int) -> bool:
        joined, before = self.joined, 1 << 30
        while True:
            seam = joined.get(a << 20 | b)
            if seam is not None and seam < before:
                return False
            if a < 256 and b < 256:
                return True
            if a > b:
                before, a = a, self.right[a]
            else:
                before, b = b + 1, self.left[b]

    def _automaton(self, pieces: list[bytes]) -> None:
        """States are the prefixes of pieces, by number. Of a state: what it leads to by a byte (``step``, at
        state << 8 | byte, filled in as it is met), the state of its longest proper suffix, and the pieces of two
        bytes or more that end there, longest first, as (piece, size)."""
        self.step: dict[int, int] = {}
        kids: list[dict[int, int]] = [{}]
        own: list[tuple[int, int] | None] = [None]
        for i, p in enumerate(pieces):
            at = 0
            for byte in p:
                to = kids[at].get(byte)
                if to is None:
                    to = kids[at][byte] = len(kids)
                    kids.append({})
                    own.append(None)
                at = to
            if len(p) > 1:
                own[at] = (i, len(p))
        self.kids, self.fail, self.ending = kids, [0] * len(kids), [()] * len(kids)
        none: dict[int, int] = {}
        for at, some in enumerate(kids):
            if not some:
                kids[at] = none  # one for all that lead nowhere
        row = list(kids[0].values())
        for byte, to in kids[0].items():
            self.step[byte] = to
        while row:
            following = []
            for at in row:
                back = self.fail[at]
                self.ending[at] = (own[at], *self.ending[back]) if own[at] else self.ending[back]
                for byte, to in kids[at].items():
                    self.fail[to] = self._follow(back, byte)
                    following.append(to)
            row = following

    def _follow(self, at: int, byte: int) -> int:
        while byte not in self.kids[at]:
            if not at:
                return 0
            at = self.fail[at]
        return self.kids[at][byte]

    def insert(self, words: list[str]) -> None:
        """Encodes new words. Sorted, they are the leaves of their trie in depth-first order, of which
        only the path to the present word is held: at each depth the last token of the prefix, the
        depth at which that token begins, and the automaton's state, which knows the pieces that end
        there. A word keeps the states that it shares with the one before it."""
        step, ending, out, stable, known, follow, is_stable = self.step, self.ending, self.out, self.stable, self.words.new, self._follow, self.is_stable
        last, begin, states, before = [-1], [0], [0], b""
        for data, word in sorted([(w.encode(), w) for w in words]):
            size, shared = len(data), 0
            most = min(len(before), size)
            if data[:most] == before[:most]:
                shared = most
            else:
                while data[shared] == before[shared]:
                    shared += 1
            del last[shared + 1 :], begin[shared + 1 :], states[shared + 1 :]
            state, i = states[shared], shared
            for byte in data[shared:]:
                edge = state << 8 | byte
                state = step.get(edge, -1)
                if state < 0:
                    state = step[edge] = follow(edge >> 8, byte)
                i += 1
                token, at = byte, i - 1
                for t, n in ending[state]:
                    if n == i:
                        token, at = t, 0
                        break
                    pair = last[i - n] << 20 | t
                    ok = stable.get(pair)
                    if ok is None:
                        ok = stable[pair] = is_stable(last[i - n], t)
                    if ok:
                        token, at = t, i - n
                        break
                last.append(token)
                begin.append(at)
                states.append(state)
            ids, at = [], size
            while at:
                ids.append(out[last[at]])
                at = begin[at]
            ids.reverse()
            known[word] = b"".join(ids)
            before = data

    def split(self, text: str) -> list[str]:
        """Words of a chunk that begins with a space, if any; those of letters alone, or of these and marks behind
        them, are most and need no pattern."""
        if text.isascii():
            core = text[1:].rstrip(MARKS)
            if core.isalpha() and text[0] == " ":
                return [text] if len(core) + 1 == len(text) else [text[: len(core) + 1], text[len(core) + 1 :]]
        if YOUNG.search(text) is None:
            return WORD.findall(text)
        if self.own_splitter is None:
            from tokenizers import Tokenizer

            self.own_splitter = Tokenizer.from_file(self.path).pre_tokenizer
        return [text[a:b] for _, (a, b) in self.own_splitter.pre_tokenize_str(text)]

    def cut(self, text: str) -> list[str]:
        """Chunks that are split into words apart from each other: the text is cut at single spaces
        between other characters. The first chunk has a space put before it as a mark, the others
        lose theirs; if the text begins with a space, it begins with two here."""
        chunks = text.split(" ")
        if not all(chunks) or "\n " in text or " \n" in text or not EDGES.isdisjoint(text):
            chunks = BETWEEN.split(text)
        chunks[0] = " " + chunks[0]
        return chunks

    def learn(self, chunks: list[str]) -> None:
        split = [self.split(c[1:] if c[:1] == " " else " " + c) for c in chunks]
        if len(self.stable) > 300_000:
            self.stable.clear()
        if len(self.step) > 300_000:
            self.step.clear()
        self.insert(self.words.lacking(set().union(*split)))
        words = self.words.new
        self.chunks.new.update((c, b"".join([words[p] for p in pieces])) for c, pieces in zip(chunks, split, strict=True))

    def encode_batch(self, batch: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all texts one after another, and how many each has."""
        texts: list[list[str | bytes | list[str]]] = []
        for text in batch:
            parts, at = [], 0
            for m in self.split_special.finditer(text) if self.special else ():
                parts += [self.cut(text[at : m.start()]), self.special[m.group()].to_bytes(4, "little")]
                at = m.end()
            texts.append([*parts, self.cut(text[at:])])
        need: set[str] = set().union(*(p for parts in texts for p in parts if isinstance(p, list)))
        if new := self.chunks.lacking(need):
            self.learn(new)
        known = self.chunks.new
        flat = [b"".join([p if isinstance(p, bytes) else b"".join([known[c] for c in p]) for p in parts]) for parts in texts]
        return np.frombuffer(b"".join(flat), np.int32), np.array([len(data) // 4 for data in flat], np.int64)

    def decode_batch(self, ids: np.ndarray, lengths: np.ndarray) -> list[str]:
        if len(ids) and (ids.min() < 0 or ids.max() >= len(self.lengths)):
            raise ValueError("an id is not in the vocabulary")
        each = self.lengths[ids]
        data = self.bytes[ragged(self.starts[ids], each)].tobytes()
        at = np.concatenate([[0], np.cumsum(each)])[np.concatenate([[0], np.cumsum(lengths)])]
        return [data[a:b].decode("utf-8", "replace") for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]


@lru_cache(maxsize=2)
def trie(path: str) -> Trie:
    """One for each worker process and vocabulary."""
    return Trie(path)


def _added(schema: T.StructType, name: str, kind: T.DataType) -> T.StructType:
    return T.StructType([f for f in schema.fields if f.name != name] + [T.StructField(name, kind)])


def _with(part: pa.RecordBatch, name: str, values: pa.Array) -> pa.RecordBatch:
    keep = [n for n in part.schema.names if n != name]
    return pa.RecordBatch.from_arrays([*(part.column(n) for n in keep), values], names=[*keep, name])


def encode(df: DataFrame, column: str = "text", out: str = "token_ids", path: str | None = None, rows: int = 2048, hold: bool = True) -> DataFrame:
    """df with the ids of a text column in ``out``, array<int>. Without ``hold``, a worker lets go of the vocabulary too at the
    end of each task."""
    path = path or vocabulary_path()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = trie(path)
        for batch in batches:
            for part in slices(batch, column, rows):
                ids, lengths = t.encode_batch([x or "" for x in part.column(column).to_pylist()])
                yield _with(part, out, list_array(pa.array(ids), lengths))
        t.forget()
        if not hold:
            del t
            trie.cache_clear()
            released()

    return df.mapInArrow(run, _added(df.schema, out, T.ArrayType(T.IntegerType())))


def decode(df: DataFrame, column: str = "token_ids", out: str = "decoded", path: str | None = None, rows: int = 2048) -> DataFrame:
    """df with the text of an array<int> column of ids in ``out``; null ids are no ids."""
    path = path or vocabulary_path()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = trie(path)
        for batch in batches:
            for part in slices(batch, column, rows, 1 << 20):
                ids = part.column(column)
                lengths = np.array([0 if n is None else n for n in ids.value_lengths().to_pylist()], np.int64)
                yield _with(part, out, pa.array(t.decode_batch(ids.flatten().to_numpy(zero_copy_only=False).astype(np.int64), lengths)))

    return df.mapInArrow(run, _added(df.schema, out, T.StringType()))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    done = decode(encode(docs).drop("text"))
    listed = F.coalesce(F.array_join("token_ids", ","), F.lit(""))
    return done.select(
        "doc_id",
        F.size("token_ids").cast("long").alias("n_tokens"),
        F.sha2(listed.cast("binary"), 256).alias("ids_sha256"),
        F.sha2(F.col("decoded").cast("binary"), 256).alias("decoded_sha256"),
    )


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents as the trainer reads them: ids in place of text."""
    return encode(docs.select("doc_id", "text", "lang", "source"), rows=256, hold=False).select("doc_id", "lang", "source", F.size("token_ids").cast("long").alias("n_tokens"), "token_ids")
