"""Byte-level BPE by longest matches with backtracking.

A piece's bytes are mapped to Latin-1, so that pyahocorasick can find, in one pass, the longest token that starts at each byte. The
encoder then walks forward: it takes the longest token whose pair with the token before could not have been merged
otherwise, and steps back to shorter ones where nothing fits. A prefix has one encoding only, so a place that led
nowhere is never tried twice, and time is linear in the piece. Whether two tokens may stand side by side follows from the
order of merges: both are taken apart, and if a merge across the border had come first, they may not. Answers are kept.

Defined results: null is an empty text, which has no ids (hash of nothing); texts of any length are encoded whole; repeated
rows each get a row; an empty table gives an empty table; extra columns are not read.
"""

from __future__ import annotations

import base64
import gc
import hashlib
from array import array
from collections.abc import Iterator
from functools import lru_cache
from itertools import islice

import ahocorasick
import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from farfield.llm.common import DOCUMENT_COLUMNS, KEPT, let_workers_import, slices

#: Pieces and pairs that a worker remembers: two generations of so many pieces, of which the older one goes when the younger is full.
REMEMBERED, REMEMBERED_PAIRS = 100_000, 300_000
_NEVER = 1 << 60
#: Pieces up to so many bytes are looked up in the trie where the walk comes by; in longer ones one pass finds the longest token of every byte.
SHORT = 64


class ByteBPE:
    def __init__(self, path: str, pattern: str):
        self.bytes_of: dict[int, bytes] = {}
        with open(path, "rb") as f:
            for line in f:
                if line.strip():
                    token, rank = line.split()
                    self.bytes_of[int(rank)] = base64.b64decode(token)
        self.pattern = regex.compile(pattern)
        self.rank_of = {t: r for r, t in self.bytes_of.items()}
        self.name = {r: str(r) for r in self.bytes_of}
        self.size = {r: len(t) for r, t in self.bytes_of.items()}
        self.found = ahocorasick.Automaton()
        for token, rank in self.rank_of.items():
            self.found.add_word(token.decode("latin-1"), rank)
        self.found.make_automaton()
        #: The longest token that begins a token, besides itself.
        self.shorter = {r: next((self.rank_of[t[:k]] for k in range(len(t) - 1, 0, -1) if t[:k] in self.rank_of), -1) for r, t in self.bytes_of.items()}
        self.merged: dict[tuple[int, int], int] = {}
        self.parts: dict[int, tuple[int, int]] = {}
        self.fits_known: dict[int, bool] = {}
        for rank in sorted(self.bytes_of):
            t = self.bytes_of[rank]
            for k in range(1, len(t)):
                a, b = self.rank_of.get(t[:k]), self.rank_of.get(t[k:])
                if a is not None and b is not None and a < rank and b < rank and self._fit(a, b):
                    self.parts[rank], self.merged[a, b] = (a, b), rank
                    break
        self.pieces = _Pieces(self)

    def _fit(self, a: int, b: int) -> bool:
        """Whether a and b stay apart when their bytes are merged in rank order.

        The pieces at the border grow from single bytes to a and b. x and y are what stands there at a time; each is next swallowed
        by a larger piece of its own side, at that piece's rank. A merge across wins if it is due before both; at equal
        rank the left place goes first.
        """
        left, right = [a], [b]
        while left[-1] in self.parts:
            left.append(self.parts[left[-1]][1])
        while right[-1] in self.parts:
            right.append(self.parts[right[-1]][0])
        x, y = left.pop(), right.pop()
        while True:
            due_left, due_right = left[-1] if left else _NEVER, right[-1] if right else _NEVER
            across = self.merged.get((x, y), _NEVER)
            if across < due_left and across <= due_right and across != _NEVER:
                return False
            if due_left == due_right == _NEVER:
                return True
            if due_left <= due_right:
                x = left.pop()
            else:
                y = right.pop()

    def fits(self, a: int, b: int) -> bool:
        pair = a << 32 | b
        known = self.fits_known.get(pair)
        if known is None:
            if len(self.fits_known) >= REMEMBERED_PAIRS:
                self.fits_known.clear()
            known = self.fits_known[pair] = self._fit(a, b)
        return known

    def encode_piece(self, piece: bytes) -> list[int]:
        whole = self.rank_of.get(piece)
        if whole is not None:
            return [whole]
        n = len(piece)
        if n <= SHORT:
            return self._encode_short(piece)
        longest = np.full(n, -1, np.int32) if n > 4096 else [-1] * n
        for end, rank in self.found.iter(piece.decode("latin-1")):
            longest[end - self.size[rank] + 1] = rank  # later ones are longer
        ids: list[int] = []
        nowhere = bytearray(n + 1)
        at, token = 0, int(longest[0])
        while at < n:
            while token >= 0 and (nowhere[at + self.size[token]] or (ids and not self.fits(ids[-1], token))):
                token = self.shorter[token]
            if token >= 0:
                ids.append(token)
                at += self.size[token]
                token = int(longest[at]) if at < n else -1
            else:
                nowhere[at] = 1
                last = ids.pop()
                at -= self.size[last]
                token = self.shorter[last]
        return ids

    def _encode_short(self, piece: bytes) -> list[int]:
        """The same walk. One pass gives the longest tokens from left to right, which are the answer if neighbours fit; else the walk goes on at the first that
        does not, and looks the longest token up only at places that it comes to."""
        text, n, fits, known, size = piece.decode("latin-1"), len(piece), self.fits, self.fits_known, self.size
        ids: list[int] = []
        last = token = -1
        for _, token in self.found.iter_long(text):
            if last >= 0 and not (fits(last, token) if (fit := known.get(last << 32 | token)) is None else fit):
                break
            ids.append(token)
            last = token
        else:
            return ids
        rank_of, shorter, prefix = self.rank_of, self.shorter, self.found.longest_prefix
        nowhere: set[int] = set()
        at, token = sum([size[i] for i in ids]), shorter[token]
        while at < n:
            if token == -2:
                end = at + prefix(text[at:])
                while (token := rank_of.get(piece[at:end], -1)) < 0:
                    end -= 1
            while token >= 0:
                if not nowhere or at + size[token] not in nowhere:
                    if last < 0 or (fits(last, token) if (fit := known.get(last << 32 | token)) is None else fit):
                        break
                token = shorter[token]
            if token >= 0:
                ids.append(token)
                at += size[token]
                last, token = token, -2
            else:
                nowhere.add(at)
                gone = ids.pop()
                at -= size[gone]
                last, token = ids[-1] if ids else -1, shorter[gone]
        return ids

    def forget(self) -> None:
        """Drops the answers kept; the tables stay."""
        self.pieces.clear()
        self.pieces.older = {}
        self.fits_known.clear()

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids))

    def encode(self, text: str) -> list[int]:
        return [i for m in self.pattern.finditer(text) for i in self.encode_piece(m[0].encode())]

    def digest(self, text: str, into: list[bytes] | None = None) -> tuple[int, str, str]:
        """Number of ids, SHA-256 of the ids, SHA-256 of the decoded bytes; the ids are appended to `into`, if it is given."""
        n, ids, decoded, first, seen = 0, hashlib.sha256(), hashlib.sha256(), True, self.pieces
        found = self.pattern.finditer(text) if len(text) > 1 << 20 else None
        some = self.pattern.findall(text) if found is None else [m[0] for m in islice(found, 1 << 16)]
        while some:
            got = list(map(seen.__getitem__, some))
            names = " ".join([g[0] for g in got])
            ids.update((names if first else " " + names).encode())
            decoded.update(b"".join([g[1] for g in got]))
            n += names.count(" ") + 1
            if into is not None:
                into.append(b"".join([g[2] for g in got]))
            first = False
            some = [] if found is None else [m[0] for m in islice(found, 1 << 16)]
        return n, ids.hexdigest(), decoded.hexdigest()


class _Pieces(dict):
    """Piece to (ids as text, decoded bytes, ids as 32-bit numbers)."""

    def __init__(self, bpe: ByteBPE):
        self.bpe, self.older = bpe, {}

    def __missing__(self, piece: str) -> tuple[str, bytes, bytes]:
        got = self.older.get(piece)
        if got is None:
            bpe = self.bpe
            ids = bpe.encode_piece(piece.encode())
            got = " ".join([bpe.name[i] for i in ids]), bpe.decode(ids), array("i", ids).tobytes()
        if len(piece) <= 64:
            if len(self) >= REMEMBERED:
                self.older = dict(self)
                self.clear()
            self[piece] = got
        return got


@lru_cache(2)
def tokenizer(path: str, pattern: str) -> ByteBPE:
    bpe = ByteBPE(path, pattern)
    KEPT["bpe"] = bpe.forget
    gc.freeze()  # the tables stay, so collections need not walk them again and again
    return bpe


def public_tokenizer() -> tuple[str, str]:
    """Path and pattern of the vocabulary to use by default; each machine has its own copy."""
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN


def digests(docs: DataFrame, path: str | None = None, pattern: str | None = None, keep: tuple[str, ...] = ("doc_id",), with_ids: bool = False) -> DataFrame:
    """The kept columns, n_tokens, ids_sha256, decoded_sha256 and, if asked for, ids of each text. Without a path, executors ask for the public one."""
    let_workers_import(docs.sparkSession)
    place = len(keep)
    names = [*keep, "n_tokens", "ids_sha256", "decoded_sha256"] + ["ids"] * with_ids

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = tokenizer(*((path, pattern) if path else public_tokenizer()))
        for b in slices(batches, keeps="bpe"):
            ids: list[bytes] = []
            got = [bpe.digest(t.as_py() or "", ids if with_ids else None) for t in b.column(place)]
            new = [pa.array([g[k] for g in got], kind) for k, kind in enumerate((pa.int64(), pa.string(), pa.string()))]
            if with_ids:
                ends = np.cumsum([0, *(g[0] for g in got)]).astype(np.int32)
                new.append(pa.ListArray.from_arrays(pa.array(ends), pa.array(np.frombuffer(b"".join(ids), np.int32))))
            yield pa.RecordBatch.from_arrays([*b.columns[:place], *new], names=names)

    columns = docs.select(*keep, F.col("text").cast("string").alias("__text"))
    ddl = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in columns.schema.fields[:-1])
    return columns.mapInArrow(run, f"{ddl}, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * with_ids)


def op8_bpe(docs: DataFrame) -> DataFrame:
    return digests(docs)


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline: the ids of each text, with its columns but the text."""
    return digests(docs, keep=tuple(c for c in DOCUMENT_COLUMNS if c != "text"), with_ids=True)
