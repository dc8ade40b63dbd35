"""Byte-level BPE: exact ids by longest matches and backtracking, and decoding.

A piece of text is mapped byte by byte to Latin-1, so that an Aho-Corasick automaton of the
vocabulary finds the longest token that starts at each byte. Tokens are then laid down greedily;
a token that would not stand beside its left neighbour after the merges is shortened, and where
nothing shorter fits the last token is taken back and that boundary is barred. Each boundary is
barred once at most, so the work is linear in the piece. Whether two tokens can be neighbours is
decided from the merges that made them, and is remembered.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

from ._blocks import table, text_column

#: Pieces and pairs that a worker remembers; memory only, results don't depend on it.
MEMO = 150_000


class _Memo(dict):
    """A dict that computes what it lacks and starts again when it is full."""

    def __init__(self, make, most: int = MEMO):
        super().__init__()
        self.make, self.most = make, most

    def __missing__(self, key):
        if len(self) >= self.most:
            self.clear()
        value = self[key] = self.make(key)
        return value


class BytePairCoder:
    """Encoder and decoder for a file of ranks (base64 token, rank) and a split pattern."""

    def __init__(self, path: str, pattern: str):
        import ahocorasick
        import regex

        with open(path, "rb") as lines:
            self.ranks = {base64.b64decode(a): int(b) for a, b in (x.split() for x in lines if x.strip())}
        self.size = max(self.ranks.values(), default=-1) + 1
        self.parts = [b""] * self.size
        for token, rank in self.ranks.items():
            self.parts[rank] = token
        self.find = regex.compile(pattern).findall
        self.longest = ahocorasick.Automaton()
        for token, rank in self.ranks.items():
            self.longest.add_word(token.decode("latin-1"), (len(token), rank))
        self.longest.make_automaton()
        self._learn_merges()
        self.shorter = [self._shorter(token) for token in self.parts]
        self.beside = _Memo(self._beside)
        self.memo = _Memo(self._packed)

    def _learn_merges(self) -> None:
        """Which two tokens each token is merged from, in the order of ranks; a token of one byte has none."""
        self.halves: list[tuple[int, int] | None] = [None] * self.size
        self.merged: dict[tuple[int, int], int] = {}
        for rank, token in enumerate(self.parts):
            if len(token) < 2:
                continue
            if (pair := self._merge_until(token, rank)) is not None:
                self.halves[rank] = pair
                self.merged[pair] = rank

    def _merge_until(self, token: bytes, rank: int) -> tuple[int, int] | None:
        """The last two parts of a token when only lower ranks merge."""
        parts = [token[i : i + 1] for i in range(len(token))]
        while len(parts) > 2:
            found = [(self.ranks.get(a + b, rank), i) for i, (a, b) in enumerate(zip(parts, parts[1:], strict=False))]
            best, i = min(found)
            if best >= rank:
                return None
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
        left, right = (self.ranks.get(x) for x in parts)
        return None if left is None or right is None else (left, right)

    def _shorter(self, token: bytes) -> int:
        """The longest token that is a proper prefix, or -1."""
        return next((self.ranks[token[:n]] for n in range(len(token) - 1, 0, -1) if token[:n] in self.ranks), -1)

    def _beside(self, key: int) -> bool:
        """Do these two tokens stay apart under the merges?

        Undo the later of the two each time, down to the parts that touch: if the parts on both
        sides of the boundary merge before the token that hides them was made, the pair is not stable.
        """
        left, right = divmod(key, self.size)
        until = self.size + 1
        while True:
            joined = self.merged.get((left, right))
            if joined is not None and joined < until:
                return False
            undo_left = left > right
            for side in ("left", "right") if undo_left else ("right", "left"):
                whole = left if side == "left" else right
                if (pair := self.halves[whole]) is not None:
                    until = whole if side == "left" else whole + 1
                    left, right = (pair[1], right) if side == "left" else (left, pair[0])
                    break
                if side == ("right" if undo_left else "left"):
                    return True
                until = whole if side == "left" else whole + 1

    def encode_bytes(self, piece: bytes) -> list[int]:
        """Ids of one piece."""
        if (whole := self.ranks.get(piece)) is not None:
            return [whole]
        n = len(piece)
        first = [-1] * n
        for end, (length, rank) in self.longest.iter(piece.decode("latin-1")):
            first[end - length + 1] = rank  # longer ones end later
        open_at = bytearray(b"\x01") * (n + 1)
        size, parts, shorter, beside = self.size, self.parts, self.shorter, self.beside
        out: list[int] = []
        at, token = 0, first[0] if n else -1
        while at < n:
            while token >= 0:
                end = at + len(parts[token])
                if open_at[end] and (not out or beside[out[-1] * size + token]):
                    break
                token = shorter[token]
            if token >= 0:
                out.append(token)
                at = end
                token = first[at] if at < n else -1
                continue
            if not out:
                raise ValueError("a byte has no token in this vocabulary")
            open_at[at] = 0
            token = out.pop()
            at -= len(parts[token])
        return out

    def _packed(self, piece: str) -> bytes:
        return np.array(self.encode_bytes(piece.encode("utf-8")), "<u4").tobytes()

    def encode(self, text: str) -> bytes:
        """Ids of a text as little-endian unsigned 32-bit integers."""
        return b"".join(map(self.memo.__getitem__, self.find(text)))

    def decode(self, ids: Iterable[int]) -> bytes:
        """The bytes that ids stand for."""
        return b"".join(map(self.parts.__getitem__, ids))


_CODERS: dict[tuple[str, str], BytePairCoder] = {}


def coder(path: str, pattern: str) -> BytePairCoder:
    """This process's coder for a vocabulary; built once in each worker."""
    if (path, pattern) not in _CODERS:
        _CODERS[path, pattern] = BytePairCoder(path, pattern)
    return _CODERS[path, pattern]


def encode_documents(docs: DataFrame, path: str, pattern: str, key: str = "doc_id", text: str = "text", keep: tuple[str, ...] = (), with_ids: bool = False) -> DataFrame:
    """Encode and decode each text: key, n_tokens, ids_sha256, decoded_sha256, the columns of keep, and ids if asked for.

    A null or empty text has no ids and the digests of nothing. Rows are independent: repeated rows
    and null keys give a row each, an empty table gives none; other columns of docs are not read.
    """
    kinds = docs.schema
    fields = [T.StructField(key, kinds[key].dataType), T.StructField("n_tokens", T.LongType()), T.StructField("ids_sha256", T.StringType()), T.StructField("decoded_sha256", T.StringType())]
    fields += [T.StructField(c, kinds[c].dataType) for c in keep] + ([T.StructField("ids", T.ArrayType(T.IntegerType(), False))] if with_ids else [])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = coder(path, pattern)
        sha = lambda x: hashlib.sha256(x).hexdigest()
        for batch in batches:
            for lo in range(0, batch.num_rows, 512):
                part = batch.slice(lo, 512)
                rows, packed = [], []
                for value in text_column(part.column(1)).to_pylist():
                    ids = own.encode(value)
                    rows.append((len(ids) // 4, sha(ids), sha(own.decode(np.frombuffer(ids, "<u4").tolist()))))
                    if with_ids:
                        packed.append(ids)
                n, a, b = zip(*rows, strict=True)
                cols = [part.column(0), pa.array(n, pa.int64()), pa.array(a, pa.string()), pa.array(b, pa.string()), *part.columns[2:]]
                if with_ids:
                    ends = np.concatenate([[0], np.cumsum(n)]).astype(np.int32)
                    cols.append(pa.ListArray.from_arrays(pa.array(ends), pa.array(np.frombuffer(b"".join(packed), "<i4"))))
                yield pa.RecordBatch.from_arrays(cols, [f.name for f in fields])

    return docs.select(key, text, *keep).mapInArrow(run, T.StructType(fields))


def vocabulary(name: str = "byte_bpe_50k.tiktoken") -> tuple[str, str]:
    """Place of a public vocabulary, and the pattern that goes with the rank files."""
    import public_tokenizers

    return public_tokenizers.path(name), public_tokenizers.PATTERN


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """op8: ids and decoded bytes of every document, as digests."""
    return encode_documents(table(spark, sf_dir, "documents"), *vocabulary())
