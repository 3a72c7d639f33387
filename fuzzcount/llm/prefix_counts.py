"""Exact token counts of every prefix of a text, without encoding prefixes one by one.

The vocabulary is a byte-level BPE whose words end in a marked symbol.  A token sequence is the encoding
of its text if and only if each neighbouring pair is; so the last token of a prefix follows from those of
shorter prefixes, and a linear pass over a word gives the count of each of its prefixes.  Words do not
share tokens, hence a text's prefix count is the sum over its whole words plus one entry of the table of
the word that the prefix cuts.  Tables are built once per distinct word and kept while they fit.

Counts equal those of the `tokenizers` library on whole texts: special strings in a text count one token
each, the library's own normaliser is applied to what lies between them.

Edge cases: a null or empty text has no tokens and the prefix table [0]; a text of blanks has no tokens; a
long word takes time in proportion to its length; null ids and repeated rows are counted like others.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import ahocorasick
import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Fixed values of the tokenizer's pre-tokenisation: white space, and what forms a word.
WHITE = "\t\n\x0b\x0c\r \x85\xa0  -     　"
WORDS = rf"'s|'t|'re|'ve|'m|'ll|'d|\p{{L}}+|\p{{N}}|[^{WHITE}\p{{L}}\p{{N}}]+"
CACHED_WORDS, CACHED_PAIRS = 1_000_000, 1_000_000
NEVER = 1 << 60


def byte_symbols() -> dict[str, int]:
    """The printable symbols by which byte-level vocabularies write the 256 bytes."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    others = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(others)}


class PrefixCounter:
    """Prefix tables of the words of one vocabulary file."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as file:
            spec = json.load(file)
        self.end = spec["model"]["end_of_word_suffix"] or ""
        symbols = byte_symbols()

        def parse(token: str) -> tuple[bytes, bool]:
            last = bool(self.end) and token.endswith(self.end)
            return bytes(symbols[c] for c in (token[: -len(self.end)] if last else token)), last

        special = {t["content"] for t in spec["added_tokens"]}
        self.tokens = [(b"", False), *sorted({parse(t) for t in spec["model"]["vocab"] if t not in special})]
        number = {token: i for i, token in enumerate(self.tokens)}
        merges = [m.split(" ") if isinstance(m, str) else m for m in spec["model"]["merges"]]
        self.ranks = {(parse(a), parse(b)): i for i, (a, b) in enumerate(merges)}
        self.found = ahocorasick.Automaton()  # every token that ends at a place of a word: its size, its number, its number at a word's end
        for data in {data for data, _ in self.tokens[1:]}:
            self.found.add_word(data.decode("latin-1"), (len(data), number.get((data, False), 0), number.get((data, True), 0)))
        self.found.make_automaton()
        self.special = regex.compile("|".join(map(regex.escape, sorted(special)))) if special else None
        self.words = regex.compile(WORDS)
        self.normal = Tokenizer.from_file(path).normalizer
        self.totals: dict[str, int] = {}
        self.pairs: dict[int, bool] = {}

    def stands(self, first: int, second: int) -> bool:
        """Whether a token may follow another (0: begin a word): merging their text by rank gives just these two."""
        (a, _), (b, marked) = self.tokens[first], self.tokens[second]
        text = a + b
        parts = [(text[i : i + 1], False) for i in range(len(text))]
        parts[-1] = (parts[-1][0], marked)
        ranks = [self.ranks.get(pair, NEVER) for pair in zip(parts, parts[1:], strict=False)]
        while ranks and (least := min(ranks)) < NEVER:
            at = ranks.index(least)
            parts[at : at + 2] = [(parts[at][0] + parts[at + 1][0], parts[at + 1][1])]
            del ranks[at]
            for i in (at - 1, at):
                if 0 <= i < len(ranks):
                    ranks[i] = self.ranks.get((parts[i], parts[i + 1]), NEVER)
        if len(self.pairs) >= CACHED_PAIRS:
            self.pairs.clear()
        result = self.pairs[first << 20 | second] = parts == ([self.tokens[first], self.tokens[second]] if first else [self.tokens[second]])
        return result

    def ends(self, data: bytes, every: bool) -> list[int]:
        """The count of each prefix of a word's bytes as a word of its own; unless `every`, of the last one only."""
        n = len(data)
        last, inner, counts = [0] + [-1] * n, [0] * (n + 1), [0] * (n + 1)
        known, marks = self.pairs, bool(self.end)
        for at, (size, plain, marked) in self.found.iter(data.decode("latin-1")):
            before = last[at + 1 - size]
            if before < 0:
                continue
            if plain and last[at + 1] < 0:
                fits = known.get(before << 20 | plain)
                if fits or (fits is None and self.stands(before, plain)):
                    last[at + 1], inner[at + 1] = plain, inner[at + 1 - size] + 1
            if marked and (every or at == n - 1) and not counts[at + 1]:
                fits = known.get(before << 20 | marked)
                if fits or (fits is None and self.stands(before, marked)):
                    counts[at + 1] = inner[at + 1 - size] + 1
        return counts if marks else inner

    def table(self, word: str) -> np.ndarray:
        """counts[i]: tokens of the first i characters of a word, taken as a text of their own."""
        data = word.encode()
        ends, counts, at = self.ends(data, True), [0], 0
        for c in word:
            at += len(c.encode())
            counts.append(ends[at])
        if len(word) == 3 and word[0] == "'" and self.words.fullmatch(word[:2]) is None:
            counts[2] = counts[1] + self.total(word[1])  # cut there, the contraction falls into two words
        return np.array(counts, np.int32)

    def total(self, word: str) -> int:
        """The last entry of the word's table."""
        if (found := self.totals.get(word)) is None:
            if len(self.totals) >= CACHED_WORDS:
                self.totals.clear()
            found = self.totals[word] = self.ends(word.encode(), False)[-1]
        return found

    def segments(self, text: str) -> Iterator[tuple[str, bool]]:
        """(text, special) in order; what is not special is normalised."""
        at = 0
        if "<|" in text and self.special:
            for found in self.special.finditer(text):
                if found.start() > at:
                    yield self.normalised(text[at : found.start()]), False
                yield found.group(), True
                at = found.end()
        if at < len(text):
            yield self.normalised(text[at:]), False

    def normalised(self, text: str) -> str:
        return text.lower() if text.isascii() else self.normal.normalize_str(text)

    def word_ends(self, text: str) -> np.ndarray:
        """Token counts of the prefixes that end with a word or special string; the last one is the text's."""
        found: list[int] = []
        for part, special in self.segments(text):
            if special:
                found.append(1)
                continue
            words = self.words.findall(part)
            counts = list(map(self.totals.get, words))
            if None in counts:
                counts = [self.total(word) if count is None else count for word, count in zip(words, counts, strict=True)]
            found += counts
        return np.cumsum(found, dtype=np.int64)

    def every_prefix(self, text: str) -> tuple[str, np.ndarray]:
        """The normalised text and the token count of each of its prefixes (a special string counts when whole)."""
        parts, tables, total = [], [np.zeros(1, np.int64)], 0
        for part, special in self.segments(text):
            parts.append(part)
            counts = np.empty(len(part), np.int64)
            if special:
                counts[:] = total
                total += 1
                counts[-1] = total
            else:
                at = 0
                for found in self.words.finditer(part):
                    counts[at : found.start()] = total
                    table = self.table(found.group())
                    counts[found.start() : found.end()] = total + table[1:]
                    total += int(table[-1])
                    at = found.end()
                counts[at:] = total
            tables.append(counts)
        return "".join(parts), np.concatenate(tables)

    def fits(self, text: str, budget: int) -> str:
        """The longest prefix of the normalised text of which each shorter prefix fits the budget too."""
        normal, counts = self.every_prefix(text)
        over = np.flatnonzero(counts > budget)
        return normal[: over[0] - 1] if len(over) else normal


_LOADED: dict[str, PrefixCounter] = {}


def counter(path: str) -> PrefixCounter:
    if path not in _LOADED:
        _LOADED[path] = PrefixCounter(path)
    return _LOADED[path]


COUNTED = "doc_id bigint, n_bytes bigint, n_tokens bigint"


def token_counts(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes and n_tokens of every whole text; `vocabulary` is a file that every machine has."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = counter(vocabulary)
        for batch in batches:
            texts = batch.column(1)
            tokens = []
            for text in texts:
                ends = known.word_ends(text.as_py())
                tokens.append(int(ends[-1]) if len(ends) else 0)
            yield pa.RecordBatch.from_arrays([batch.column(0), pc.binary_length(texts).cast(pa.int64()), pa.array(tokens, pa.int64())], names=["doc_id", "n_bytes", "n_tokens"])

    return docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text")).mapInArrow(count, COUNTED)


def prefix_table(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, the normalised text, and the token count of each of its prefixes (entry i: the first i characters)."""

    def tables(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = counter(vocabulary)
        for batch in batches:
            for row_id, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                normal, counts = known.every_prefix(text)
                yield pa.RecordBatch.from_arrays([pa.array([row_id], pa.int64()), pa.array([normal]), pa.array([counts.tolist()], pa.list_(pa.int32()))], names=["doc_id", "normal_text", "prefix_tokens"])

    return docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text")).mapInArrow(tables, "doc_id bigint, normal_text string, prefix_tokens array<int>")
