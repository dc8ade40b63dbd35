"""Token counts by a linear longest-match automaton.

A trie of the vocabulary gets failure links. When a word cannot go on from a trie node, the
longest tokens that cover what was read are popped and the walk goes on at the link; how many
tokens are popped is computed once for each node, so that the greedy longest-match-first split of a
word is counted in one pass over its bytes and no piece is built.
"""

from __future__ import annotations

import json
from collections import deque
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

from ._blocks import table, text_column
from .bpe import _Memo

#: The symbol behind the last byte of a word; a token that ends words ends with it.
END = 256
#: Fixed value: how words are cut, as the vocabulary's own description has it.
WORDS = r"""'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"""


class LongestMatchCounter:
    """Counts greedy longest-match tokens of words over a vocabulary of byte strings, some only for word ends."""

    def __init__(self, tokens: Iterable[tuple[bytes, bool]]):
        self.next: list[dict[int, int]] = [{}]
        whole = [False]
        for token, last in tokens:
            node = 0
            for symbol in (*token, END) if last else token:
                if symbol not in self.next[node]:
                    self.next[node][symbol] = len(self.next)
                    self.next.append({})
                    whole.append(False)
                node = self.next[node][symbol]
            whole[node] = node > 0
        self.fail = [-1] * len(self.next)
        self.pops = [0] * len(self.next)
        queue = deque([0])
        while queue:
            up = queue.popleft()
            for symbol, node in self.next[up].items():
                queue.append(node)
                if whole[node]:
                    self.fail[node], self.pops[node] = 0, 1
                    continue
                back, popped = self.fail[up], self.pops[up]
                while back >= 0 and symbol not in self.next[back]:
                    popped += self.pops[back]
                    back = self.fail[back]
                if back >= 0:
                    self.fail[node], self.pops[node] = self.next[back][symbol], popped

    def count(self, word: bytes) -> int:
        """Tokens of one word; -1 if the vocabulary cannot cover it."""
        if not word:
            return 0
        node = n = 0
        go, fail, pops = self.next, self.fail, self.pops
        for symbol in (*word, END):
            while (to := go[node].get(symbol)) is None:
                if fail[node] < 0:
                    # A token that is not only for word ends may stand there too: nothing is left.
                    if symbol == END and node == 0:
                        return n
                    return -1
                n += pops[node]
                node = fail[node]
            node = to
        while node:
            if fail[node] < 0:
                return -1
            n += pops[node]
            node = fail[node]
        return n


def byte_symbols() -> dict[str, int]:
    """The printable characters that byte-level vocabularies write bytes as, from their rule."""
    plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    rest = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


def read_vocabulary(path: str) -> list[tuple[bytes, bool]]:
    """Tokens of a vocabulary file with word ends: bytes, and if the token ends a word."""
    with open(path, encoding="utf-8") as f:
        model = json.load(f)["model"]
    suffix, of = model.get("end_of_word_suffix") or "", byte_symbols()
    out = []
    for token in model["vocab"]:
        last = bool(suffix) and token.endswith(suffix)
        bare = token.removesuffix(suffix) if last else token
        if all(c in of for c in bare):
            out.append((bytes(of[c] for c in bare), last))
    return out


class TokenCounter:
    """Words and tokens of whole texts."""

    def __init__(self, path: str, words: str = WORDS):
        import unicodedata

        import regex

        self.automaton = LongestMatchCounter(read_vocabulary(path))
        self.find = regex.compile(words).findall
        self.normal = lambda text: text.lower() if text.isascii() else unicodedata.normalize("NFC", text).lower()
        self.memo = _Memo(self._word)

    def _word(self, word: str) -> int:
        return n if (n := self.automaton.count(word.encode("utf-8"))) >= 0 else 1

    def count(self, text: str) -> tuple[int, int]:
        words = self.find(self.normal(text))
        return len(words), sum(map(self.memo.__getitem__, words))


_COUNTERS: dict[str, TokenCounter] = {}


def count_tokens(docs: DataFrame, path: str, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, n_words and n_tokens of each text under greedy longest-match-first pieces.

    Texts are brought to NFC and lower case. A word that the vocabulary cannot cover counts as one
    unknown token. A null or empty text has 0 of both; repeated rows and null keys give a row each.
    """
    fields = [T.StructField(key, docs.schema[key].dataType), T.StructField("n_words", T.LongType()), T.StructField("n_tokens", T.LongType())]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if path not in _COUNTERS:
            _COUNTERS[path] = TokenCounter(path)
        count = _COUNTERS[path].count
        for batch in batches:
            for lo in range(0, batch.num_rows, 512):
                part = batch.slice(lo, 512)
                words, tokens = zip(*map(count, text_column(part.column(1)).to_pylist()), strict=True)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(words, pa.int64()), pa.array(tokens, pa.int64())], [f.name for f in fields])

    return docs.select(key, text).mapInArrow(run, T.StructType(fields))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """op7: token counts of every document."""
    import public_tokenizers

    return count_tokens(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))
