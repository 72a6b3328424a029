"""Byte-level BPE encoding and decoding in linear time.

Bytes become Latin-1 characters, so that an Aho-Corasick automaton of the vocabulary finds, in one pass, the
longest token that starts at each byte. Encoding walks from longest matches and steps back to shorter prefixes
where two neighbouring tokens could not stand side by side after the merges; that test is memoised. A prefix has
exactly one encoding, so a position that led nowhere once never has to be entered again: time is linear.
"""

from __future__ import annotations

import base64
import functools
import struct
from collections.abc import Iterator

import ahocorasick
import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from factbench.llm.common import text_slices, tidy


class ByteBpe(dict):
    """Maps a piece of text to its ids, packed as little-endian unsigned 32-bit integers.

    It is itself the bounded memo of short pieces: looking up a missing piece encodes it.
    """

    most, longest_kept = 400_000, 64

    def __init__(self, path: str, pattern: str):
        super().__init__()
        with open(path, "rb") as lines:
            pairs = [line.split() for line in lines if line.strip()]
        self.ranks = {base64.b64decode(token): int(rank) for token, rank in pairs}
        self.tokens = dict(sorted((rank, token) for token, rank in self.ranks.items()))
        self.find = regex.compile(pattern).findall
        self.beside: dict[int, bool] = {}
        #: The last two parts that make up each token that merges can reach; None for single bytes.
        self.split: dict[int, tuple[int, int] | None] = {}
        rising = True
        for token, rank in self.ranks.items():
            parts, steps = self._merged(token)
            if parts == [rank]:
                self.split[rank] = steps[-1][1:] if steps else None
                rising &= all(x[0] <= y[0] for x, y in zip(steps, steps[1:], strict=False))
        #: Whether the merges of every token never fall in rank, as those of trained vocabularies do.
        self.rising = rising
        self.ends: dict[int, list[tuple[bytes, float]]] = {}
        self.starts: dict[int, list[tuple[bytes, float]]] = {}
        self.automaton = ahocorasick.Automaton()
        for rank in self.split:
            self.automaton.add_word(self.tokens[rank].decode("latin-1"), (rank, len(self.tokens[rank])))
        self.automaton.make_automaton()
        known = {self.tokens[rank]: rank for rank in self.split}
        self.size = {rank: len(token) for token, rank in known.items()}
        #: For each token the longest shorter token that begins it; None where there is none.
        self.shorter = {rank: next((known[token[:n]] for n in range(len(token) - 1, 0, -1) if token[:n] in known), None) for token, rank in known.items()}

    def _merged(self, piece: bytes) -> tuple[list[int], list[tuple[int, int, int]]]:
        """The definition: merge the lowest-ranked neighbouring pair, leftmost first, until none is left. For short pieces.

        Returns the ids, and each merge as its rank and the ids of its two parts.
        """
        parts = [piece[i : i + 1] for i in range(len(piece))]
        ranks, steps = self.ranks, []
        while len(parts) > 1:
            pairs = [ranks.get(a + b, 1 << 60) for a, b in zip(parts, parts[1:], strict=False)]
            low = min(pairs)
            if low == 1 << 60:
                break
            at = pairs.index(low)
            steps.append((low, ranks[parts[at]], ranks[parts[at + 1]]))
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return [ranks[p] for p in parts], steps

    def _edge(self, token: int, side: int) -> list[tuple[bytes, float]]:
        """The parts at one end of a token as merges build it, smallest first, each with the rank of the merge that ends it."""
        kept = self.ends if side else self.starts
        found = kept.get(token)
        if found is None:
            chain = [token]
            while (parts := self.split[chain[-1]]) is not None:
                chain.append(parts[side])
            chain.reverse()
            found = kept[token] = [(self.tokens[t], r) for t, r in zip(chain, [*chain[1:], float("inf")], strict=True)]
        return found

    def _compatible(self, left: int, right: int) -> bool:
        """Whether the merges of both tokens' bytes together end with these two tokens."""
        key = left << 32 | right
        known = self.beside.get(key)
        if known is None:
            if len(self.beside) >= 200_000:
                self.beside.clear()
            known = self.beside[key] = self._apart(left, right) if self.rising else self._merged(self.tokens[left] + self.tokens[right])[0] == [left, right]
        return known

    def _apart(self, left: int, right: int) -> bool:
        """The same by walking both edges at the seam in the order of merges; for vocabularies whose merges rise in rank.

        A merge across the seam comes first if its rank is below those that end the parts beside it; of equal
        ranks the leftmost comes first.
        """
        ends, starts, ranks = self._edge(left, 1), self._edge(right, 0), self.ranks
        i = j = 0
        while True:
            (a, ends_at), (b, starts_at) = ends[i], starts[j]
            across = ranks.get(a + b)
            if across is not None and across < ends_at and across <= starts_at:
                return False
            if i + 1 == len(ends) and j + 1 == len(starts):
                return True
            if ends_at <= starts_at:
                i += 1
            else:
                j += 1

    def ids(self, piece: bytes) -> list[int]:
        """The ids of one piece, as the merges give them."""
        whole = self.ranks.get(piece)
        if whole is not None:
            return [whole]
        n = len(piece)
        longest: list[int | None] = [None] * n
        for end, (rank, length) in self.automaton.iter(piece.decode("latin-1")):
            longest[end + 1 - length] = rank  # ends rise, so the last is the longest
        size, shorter, compatible, beside = self.size, self.shorter, self._compatible, self.beside
        dead = bytearray(n + 1)
        out: list[int] = []
        at, token = 0, longest[0]
        while at < n:
            while token is not None:
                after = at + size[token]
                if not dead[after]:
                    if not out:
                        break
                    fits = beside.get(out[-1] << 32 | token)
                    if fits or fits is None and compatible(out[-1], token):
                        break
                token = shorter[token]
            if token is not None:
                out.append(token)
                at = after
                token = longest[at] if at < n else None
            else:
                dead[at] = 1
                token = out.pop()
                at -= size[token]
                token = shorter[token]
        return out

    def __missing__(self, piece: str) -> bytes:
        ids = self.ids(piece.encode())
        packed = struct.pack(f"<{len(ids)}I", *ids)
        if len(piece) <= self.longest_kept:
            if len(self) >= self.most:
                self.clear()
            self[piece] = packed
        return packed

    def forget(self) -> None:
        """Drop all memos."""
        for memo in (self, self.beside, self.ends, self.starts):
            memo.clear()
        tidy()

    def encode(self, text: str) -> bytes:
        return b"".join(map(self.__getitem__, self.find(text)))

    def decode(self, packed: bytes) -> bytes:
        return b"".join(map(self.tokens.__getitem__, np.frombuffer(packed, "<u4").tolist()))


@functools.lru_cache(maxsize=2)
def load(path: str, pattern: str) -> ByteBpe:
    """One codec a worker process; the vocabulary file is read where the work runs."""
    return ByteBpe(path, pattern)


def _mapped(df: DataFrame, path: str, pattern: str, source: str, fields: list[tuple[str, object]], work, carry: list[str] | None) -> DataFrame:
    new = {name for name, _ in fields}
    names = [c for c in (df.columns if carry is None else carry) if c not in new]
    schema = T.StructType([*[df.schema[c] for c in names], *[T.StructField(name, kind) for name, kind in fields]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = load(path, pattern)
        # a slice at a time, so that results of very long texts don't pile up
        for part in text_slices(batches, place=len(names), most=2 << 20):
            added = work(codec, part.column(len(names)).to_pylist())
            yield pa.RecordBatch.from_arrays([*part.columns[: len(names)], *[pa.array(a, pa.binary()) for a in added]], names=[f.name for f in schema.fields])
        codec.forget()  # the worker may go on to other work

    return df.select(*names, F.col(source).alias("_in")).mapInArrow(run, schema)


def encode(df: DataFrame, path: str, pattern: str, text: str = "text", ids: str = "ids", decoded: str | None = None, carry: list[str] | None = None) -> DataFrame:
    """Add ``ids``, the whole text's token ids as packed little-endian unsigned 32-bit integers.

    ``decoded`` names a further binary column: the ids decoded again, for a round-trip check in the same pass.
    Null texts count as empty and give an empty value; repeated rows give repeated results; an empty table gives
    an empty table; other columns are carried along (only those in ``carry``, if given), and one with the name of a
    new column gives way to it. No special tokens.
    """
    fields = [(ids, T.BinaryType())] + ([(decoded, T.BinaryType())] if decoded else [])

    def work(codec: ByteBpe, texts: list) -> list[list]:
        packed = [codec.encode(t) if t else b"" for t in texts]
        return [packed, [codec.decode(p) for p in packed]] if decoded else [packed]

    return _mapped(df, path, pattern, text, fields, work, carry)


def decode(df: DataFrame, path: str, pattern: str, ids: str = "ids", out: str = "bytes") -> DataFrame:
    """Add ``out``, the bytes that packed ``ids`` stand for; null ids give an empty value, unknown ids an error."""
    return _mapped(df, path, pattern, ids, [(out, T.BinaryType())], lambda codec, rows: [[codec.decode(p) if p else b"" for p in rows]], None)
