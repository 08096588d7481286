"""Exact token counts at every prefix of a text, for byte-level merge vocabularies.

Within a piece (the unit that the vocabulary's split pattern makes) a dynamic
program over byte positions keeps the last token and the number of tokens of
every prefix: the encoding of a prefix is the encoding of a shorter prefix and
one further token, and that token is the only one that ends there and forms a
stable pair with the token before it. Counts of pieces add up, so a document's
table of cumulative counts answers how many tokens any prefix has, and where a
budget ends, without encoding anything again.

Defined cases: a null text counts as empty and has no tokens; strings of
special tokens inside a text are one token each, as the library has it by
default; very long pieces are handled like any other; an empty table gives an
empty result.
"""

from __future__ import annotations

import json
import re
from collections.abc import Iterator

import ahocorasick
import numpy as np
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from spreadmax.llm.common import append_columns, text_bytes

LIMIT = 1024
#: Fixed value: the published split pattern of this family of vocabularies.
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Counts of pieces that one worker remembers.
CACHE = 600_000
_SPACE_RUN = re.compile(r" \s")


def _byte_letters() -> dict[str, int]:
    """The letters that stand for bytes in such vocabularies: printable ones for themselves, others from 256 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    others = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(others)}


class MergeVocabulary:
    """Tokens as byte strings in the order of their merges, and the pairs they came from."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        letters = _byte_letters()
        raw = lambda s: bytes(letters[c] for c in s)
        self.specials = [t["content"] for t in spec["added_tokens"]]
        special = set(self.specials)
        merges = [m if isinstance(m, list) else m.split(" ") for m in spec["model"]["merges"]]
        self.rank: dict[bytes, int] = {raw(s): -1 for s in spec["model"]["vocab"] if len(s) == 1 and s not in special}
        for i, b in enumerate(sorted(self.rank)):
            self.rank[b] = i - 256
        self.parts: list[tuple[int, int]] = []
        self.joined: dict[tuple[int, int], int] = {}
        for i, (a, b) in enumerate(merges):
            a, b = self.rank[raw(a)], self.rank[raw(b)]
            self.parts.append((a, b))
            self.joined[a, b] = i
            self.rank.setdefault(raw(merges[i][0]) + raw(merges[i][1]), i)
        self.longest = max(map(len, self.rank))


class PrefixCounter:
    """The dynamic program of pieces, with a bounded memory of pieces seen."""

    def __init__(self, vocabulary: MergeVocabulary, cache: int = CACHE):
        self.v = vocabulary
        self.split = regex.compile(SPLIT)
        self.special = regex.compile("|".join(regex.escape(s) for s in vocabulary.specials)) if vocabulary.specials else None
        #: For each left token: which right tokens are stable beside it; at -1000 the token itself.
        self.stable = _Memory(lambda token: {-1000: token})
        self.pairs = 0  # that `stable` holds
        self.cache = cache
        self.ending = ahocorasick.Automaton()
        for token, i in vocabulary.rank.items():
            self.ending.add_word(token.decode("latin-1"), (i, len(token)))
        self.ending.make_automaton()
        self.counts = _Memory(self._piece)
        self.first = _Memory(lambda chunk: sum(map(self.counts.__getitem__, self.split.findall(chunk))))
        self.later = _Memory(lambda chunk: sum(map(self.counts.__getitem__, self.split.findall(" " + chunk))))

    def is_stable(self, left: int, right: int) -> bool:
        """Whether the two tokens stay two tokens when their bytes are encoded together.

        The seam between them is undone from the later merge to the earlier one;
        a merge across the seam that comes before the merges on both sides would
        have been taken instead.
        """
        a, b, bound = left, right, len(self.v.parts) + 1
        answer = None
        while answer is None:
            across = self.v.joined.get((a, b))
            if across is not None and across < bound:
                answer = False
            elif a < 0 and b < 0:
                answer = True
            elif a > b:  # the left token is the later merge: it gives way to its right half
                bound, a = a, self.v.parts[a][1]
            else:  # of equal merges the one further left comes first
                bound, b = b + 1, self.v.parts[b][0]
        return answer

    def table(self, piece: bytes) -> list[int]:
        """The number of tokens of every byte prefix, from the empty one to the whole."""
        count, follow, done, stable = [0], [{}], 0, self.stable
        # The automaton gives the tokens that end at each byte, the longest first.
        for at, (token, size) in self.ending.iter(piece.decode("latin-1")):
            if at < done:
                continue
            start = at + 1 - size
            if start:
                fits = follow[start].get(token)
                if fits is None:
                    fits = follow[start][token] = self.is_stable(follow[start][-1000], token)
                    self.pairs += 1
                if not fits:
                    continue
            done += 1
            count.append(count[start] + 1)
            follow.append(stable[token])
        return count

    def pieces(self, text: str) -> Iterator[tuple[str, bool]]:
        """Pieces in order; special tokens are flagged."""
        if self.special is None or not self.special.search(text):
            for p in self.split.findall(text):
                yield p, False
            return
        at = 0
        for m in self.special.finditer(text):
            for p in self.split.findall(text[at : m.start()]):
                yield p, False
            yield m[0], True
            at = m.end()
        for p in self.split.findall(text[at:]):
            yield p, False

    def total(self, text: str) -> int:
        counts = self.counts
        if self.special is not None and self.special.search(text):
            found = sum(1 if special else counts[p] for p, special in self.pieces(text))
        elif _SPACE_RUN.search(text):
            found = sum(map(counts.__getitem__, self.split.findall(text)))
        else:
            # No piece reaches over a space that a non-space follows, so what lies between spaces counts by itself.
            chunks = text.split(" ")
            found = self.first[chunks[0]] + sum(map(self.later.__getitem__, chunks[1:]))
        self.trim()
        return found

    def _piece(self, piece: str) -> int:
        return self.table(piece.encode("utf-8", "surrogatepass"))[-1]

    def trim(self) -> None:
        """Forget pieces and pairs beyond the bound."""
        if self.pairs > self.cache:
            self.stable.clear()
            self.pairs = 0
        for memory in (self.counts, self.first, self.later):
            if len(memory) > self.cache:
                memory.clear()

    def prefixes(self, text: str) -> PrefixTable:
        return PrefixTable(self, text)


class _Memory(dict):
    """Values by key, found by `find` when first asked for."""

    def __init__(self, find):
        super().__init__()
        self.find = find

    def __missing__(self, key):
        self[key] = found = self.find(key)
        return found


class PrefixTable:
    """Cumulative counts of one text: answers for all its prefixes."""

    def __init__(self, counter: PrefixCounter, text: str):
        self.counter, self.text = counter, text
        self.kinds = list(counter.pieces(text))
        counts = [1 if special else counter.counts[p] for p, special in self.kinds]
        counter.trim()
        self.ends = np.cumsum([0, *[len(p) for p, _ in self.kinds]])
        self.sums = np.cumsum([0, *counts])

    def count(self, chars: int) -> int:
        """Tokens of text[:chars]. Only the end of the prefix is split anew: the piece
        that is cut, and white space before it, which may group otherwise there."""
        k = int(np.searchsorted(self.ends, chars, "right")) - 1
        while k > 0 and (self.kinds[k - 1][0].isspace() and not self.kinds[k - 1][1]):
            k -= 1
        tail = self.text[self.ends[k] : chars]
        return int(self.sums[k]) + (self.counter.total(tail) if tail else 0)

    def fit(self, budget: int) -> int:
        """Characters of the longest prefix that ends with a piece (not white space) and has at most `budget` tokens."""
        k = int(np.searchsorted(self.sums, budget, "right")) - 1
        while k > 0 and self.kinds[k - 1][0].isspace():
            k -= 1
        return int(self.ends[k])


_COUNTERS: dict[str, PrefixCounter] = {}


def _counter(path: str) -> PrefixCounter:
    """One vocabulary per Python worker."""
    if path not in _COUNTERS:
        _COUNTERS[path] = PrefixCounter(MergeVocabulary(path))
    return _COUNTERS[path]


def token_counts(docs: DataFrame, vocabulary: str, limit: int = LIMIT, prefixes: bool = False) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit, fit_bytes (bytes of the text that `limit` tokens hold).

    With `prefixes`, also piece_ends and piece_tokens: the table of cumulative
    counts at the ends of pieces, in characters and tokens. `vocabulary` is the
    path of a byte-level vocabulary file, readable on every executor.
    """
    fields = [("n_bytes", T.LongType()), ("n_tokens", T.LongType()), ("over_limit", T.BooleanType()), ("fit_bytes", T.LongType())]
    if prefixes:
        fields += [("piece_ends", T.ArrayType(T.LongType())), ("piece_tokens", T.ArrayType(T.LongType()))]

    def maker():
        counter = _counter(vocabulary)

        def step(texts):
            rows = []
            for data in text_bytes(texts):
                text = data.decode("utf-8", "replace")
                n = counter.total(text)
                over = n > limit
                table = counter.prefixes(text) if over or prefixes else None
                fit = len(text[: table.fit(limit)].encode()) if over else len(data)
                rows.append((len(data), n, over, fit, *((table.ends.tolist(), table.sums.tolist()) if prefixes else ())))
            return list(zip(*rows, strict=True)) if rows else [[]] * len(fields)

        return step

    work = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return append_columns(work, ["text"], fields, maker).drop("text")
