"""Token counts by heap-and-linked-list byte-pair merging.

A pretoken's bytes form a linked list of symbols. A heap holds the adjacent pairs that have a merge rank; the
lowest rank (leftmost on ties) is popped and merged until no pair is left. The count is the number of initial
symbols minus the number of merges; token identifiers are never produced. Counts of pretokens are memoised per
Python worker in a table of bounded size, so common words cost one look-up.

Nulls and empty texts count 0 tokens. Repeated rows are counted each on their own. A special string inside a
text counts as one token, as the library does by default.
"""

from __future__ import annotations

import heapq
import json

from pyspark.sql import DataFrame

from .texts import map_texts, per_worker

#: The pretoken pattern of byte-level vocabularies (fixed value).
PRETOKEN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


#: Marks that always are a pretoken of their own at the end of a piece, after a letter.
ENDS = ".,"


def word_before_end(piece: str) -> bool:
    """True if the character before the last is a letter up to Latin-1, so the last begins a new pretoken."""
    c = piece[-2:-1]
    return c.isalpha() and c <= "\xff" and len(piece) <= 64


def byte_alphabet() -> dict[int, str]:
    """The printable stand-in of each byte in byte-level vocabularies: printable Latin-1 stays, the rest moves past 255."""
    keep = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    table = {b: chr(b) for b in keep}
    for extra, b in enumerate(b for b in range(256) if b not in table):
        table[b] = chr(256 + extra)
    return table


def load_merges(path: str) -> tuple[dict[tuple[str, str], int], list[str]]:
    """Merge ranks and special strings of a byte-level tokenizer file."""
    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    pairs = (tuple(m) if isinstance(m, list) else tuple(m.split(" ", 1)) for m in spec["model"]["merges"])
    return {p: rank for rank, p in enumerate(pairs)}, [t["content"] for t in spec.get("added_tokens", [])]


def count_merged(symbols: list[str], ranks: dict[tuple[str, str], int]) -> int:
    """Symbols left when the lowest-ranked adjacent pair is merged again and again."""
    n = len(symbols)
    if n < 2:
        return n
    text = list(symbols)
    after, before = list(range(1, n + 1)), list(range(-1, n - 1))
    heap = [(r, i, i + 1) for i in range(n - 1) if (r := ranks.get((text[i], text[i + 1]))) is not None]
    heapq.heapify(heap)
    merges = 0
    while heap:
        rank, left, right = heapq.heappop(heap)
        # stale when either symbol was merged since: the pair at these places no longer has this rank
        if not text[left] or right >= n or not text[right] or after[left] != right or ranks.get((text[left], text[right])) != rank:
            continue
        text[left] += text[right]
        text[right] = ""
        nxt = after[right]
        after[left] = nxt
        merges += 1
        if nxt < n:
            before[nxt] = left
            if (r := ranks.get((text[left], text[nxt]))) is not None:
                heapq.heappush(heap, (r, left, nxt))
        prev = before[left]
        if prev >= 0 and (r := ranks.get((text[prev], text[left]))) is not None:
            heapq.heappush(heap, (r, prev, left))
    return n - merges


class Counter:
    """Counts tokens of texts; ``memo_size`` bounds the table of known pieces."""

    def __init__(self, ranks: dict[tuple[str, str], int], special: list[str], memo_size: int = 300_000):
        import re

        import regex

        self.ranks, self.memo_size = ranks, memo_size
        self.joined, self.spaced = Counts(self.piece, ""), Counts(self.piece, " ")
        self.pretokens = regex.compile(PRETOKEN).findall
        # a space before a non-space always begins a pretoken, so texts can be cut there
        self.cut = re.compile(r"(?= \S)").split
        self.uneven = re.compile(r" (?=\s|\Z)").search
        self.special = re.compile("|".join(map(re.escape, sorted(special, key=len, reverse=True)))) if special else None
        self.alphabet = byte_alphabet()

    def piece(self, piece: str) -> int:
        alphabet = self.alphabet
        return sum(count_merged([alphabet[b] for b in p.encode("utf-8", "replace")], self.ranks) for p in self.pretokens(piece))

    def count(self, text: str) -> int:
        if self.special and (found := self.special.findall(text)):
            return len(found) + sum(self.count_plain(p) for p in self.special.split(text))
        return self.count_plain(text)

    def count_plain(self, text: str) -> int:
        for memo in (self.joined, self.spaced):
            if len(memo) > self.memo_size:
                memo.clear()
        if self.uneven(text):
            return sum(map(self.joined.__getitem__, self.cut(text)))
        head, *tail = text.split(" ")
        return self.joined[head] + sum(map(self.spaced.__getitem__, tail))


class Counts(dict):
    """Counts of pieces after ``before``, found when first asked for."""

    def __init__(self, count, before: str):
        self.count, self.before = count, before

    def __missing__(self, p: str) -> int:
        n = self[p[:-1]] + 1 if p[-1:] in ENDS and word_before_end(p) else self.count(self.before + p)
        if len(p) <= 64:  # long oddities are not worth keeping
            self[p] = n
        return n


def token_counts(docs: DataFrame, tokenizer_path: str, limit: int = 1024, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for each row of ``docs``.

    The vocabulary (a constant, about a megabyte) is read once on the driver and travels as a broadcast variable.
    """
    ranks, special = load_merges(tokenizer_path)
    shared = docs.sparkSession.sparkContext.broadcast((ranks, special))

    def make():
        count = per_worker("bpe", tokenizer_path, lambda: Counter(*shared.value)).count

        def rows(ids, texts):
            out = []
            for i, t in zip(ids, texts, strict=True):
                t = t or ""
                n = count(t)
                out.append((i, len(t.encode("utf-8", "replace")), n, n > limit))
            return out

        return rows

    return map_texts(docs, [id_col, text_col], make, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
