"""Benchmark decontamination with one Aho-Corasick automaton.

All windows of the normalised benchmark texts go into one automaton over word numbers, which reads each normalised
document once and reports every occurrence; word places map back to offsets in the original for cutting. Normalising
works on UTF-8 bytes: A-Z become a-z, ASCII characters other than letters and digits separate words.

Windows are made, merged and counted in Spark. A benchmark whose windows have up to ``max_nodes`` words in all (so an
automaton has no more nodes; some 50 bytes each) is one automaton, built from one broadcast. A larger one is cut into
blocks of windows by hash; each block is one automaton and one pass over the documents, one block at a time on the
driver and in the workers. The hits of the passes are merged by row. No window is dropped.

Edge cases: null texts have no words; items without words have no windows; rows of one item id are one item, rows
without an item id are one item together, which counts but has no name in the digest; an item of fewer words than a
window is one window; an empty benchmark hits nothing; an empty document table gives no rows; repeated documents and
equal or null ids are judged row by row; other columns, whatever their names, are not read (``drop_contaminated``
keeps them).
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .texts import Scratch, filter_rows, map_texts, new_key, per_worker, stored

MAX_NODES = 8_000_000

#: A-Z to a-z, digits and a-z stay, bytes beyond ASCII stay, all else becomes a space.
NORMAL = bytes(
    b + 32 if 65 <= b <= 90 else b if 97 <= b <= 122 or 48 <= b <= 57 or b >= 128 else 32 for b in range(256)
)


def normal_words(text: str | None) -> list[bytes]:
    return text.encode("utf-8", "replace").translate(NORMAL).split() if text else []


def windows(words: list[bytes], size: int) -> list[bytes]:
    """The windows of one item, their words joined by spaces."""
    return [b" ".join(words[i : i + size]) for i in range(max(1, len(words) - size + 1))] if words else []


class Scanner:
    """One automaton. ``found`` holds (window, names of its items, whether an item without a name has it)."""

    def __init__(self, found: Iterable[tuple[bytes, list[str], bool]]):
        import ahocorasick

        self.number: dict[bytes, int] = {}
        self.automaton = ahocorasick.Automaton(ahocorasick.STORE_ANY, ahocorasick.KEY_SEQUENCE)
        self.any = False
        for window, names, nameless in found:
            # 0 is any word that no window has
            key = tuple(self.number.setdefault(w, len(self.number) + 1) for w in window.split(b" "))
            self.automaton.add_word(key, (len(key), tuple(names) + (None,) * bool(nameless)))
            self.any = True
        if self.any:
            self.automaton.make_automaton()

    @classmethod
    def of(cls, items: list[tuple[object, str | None]], size: int = 10) -> Scanner:
        """From (name, text) pairs."""
        found: dict[bytes, set] = {}
        for name, text in items:
            for w in windows(normal_words(text), size):
                found.setdefault(w, set()).add(name)
        return cls((w, [str(x) for x in names if x is not None], None in names) for w, names in found.items())

    def scan(self, text: str | None) -> tuple[int, np.ndarray | None, set]:
        """Number of words, flags of hit words (None: no hit), and names of the items found (None: one without)."""
        words = normal_words(text)
        if not words or not self.any:
            return len(words), None, set()
        get, hits = self.number.get, None
        seen: set = set()
        for end, (n, names) in self.automaton.iter(tuple([get(w, 0) for w in words])):
            if hits is None:
                hits = np.zeros(len(words) + 1, np.int64)
            hits[end + 1 - n] += 1
            hits[end + 1] -= 1
            seen.update(names)
        return len(words), None if hits is None else np.cumsum(hits)[:-1] > 0, seen

    def original_spans(self, text: str) -> list[tuple[int, int]]:
        """Byte spans of the original UTF-8 text covered by hit words; neighbours are joined."""
        n, hit, _ = self.scan(text)
        if hit is None:
            return []
        raw = np.frombuffer(text.encode("utf-8", "replace").translate(NORMAL), np.uint8) != 32
        edge = np.diff(np.concatenate([[0], raw.view(np.int8), [0]]))
        begin, end = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
        on = np.diff(np.concatenate([[0], hit.view(np.int8), [0]]))
        return [(int(begin[a]), int(end[b - 1])) for a, b in zip(np.flatnonzero(on == 1), np.flatnonzero(on == -1), strict=True)]

    def cut(self, text: str) -> str:
        """The text without its hit spans."""
        raw, out, at = text.encode("utf-8", "replace"), [], 0
        for a, b in self.original_spans(text):
            out.append(raw[at:a])
            at = b
        return b"".join([*out, raw[at:]]).decode("utf-8", "replace")


def benchmark_windows(bench: DataFrame, size: int, id_col: str = "item_id", text_col: str = "text") -> DataFrame:
    """window (bytes), items (names), nameless, n (words): one row for each different window."""

    def make():
        return lambda ids, texts: [(w, None if i is None else str(i)) for i, t in zip(ids, texts, strict=True) for w in set(windows(normal_words(t), size))]

    found = map_texts(bench, [id_col, text_col], make, "window binary, item string")
    n = F.size(F.split(F.decode("window", "ISO-8859-1"), " "))
    return found.groupBy("window").agg(F.collect_set("item").alias("items"), F.bool_or(F.col("item").isNull()).alias("nameless")).withColumn("n", n)


def blocks_of(found: DataFrame, max_nodes: int) -> int:
    """Number of blocks, none of which has much more than ``max_nodes`` words in its windows."""
    words = found.agg(F.sum("n")).first()[0] or 0
    return 1 if words <= max_nodes else 2 * -(-words // max_nodes)  # blocks by hash differ in size


def shipped(found: DataFrame, block: int, blocks: int):
    """The scanner of one block in a worker: its windows pass the driver, within the bound of a block."""
    mine = found.filter(F.pmod(F.xxhash64("window"), F.lit(blocks)) == block) if blocks > 1 else found
    rows = [(bytes(r.window), r["items"], r.nameless) for r in mine.collect()]
    shared, key = found.sparkSession.sparkContext.broadcast(rows), new_key()
    return lambda: per_worker("scanner", key, lambda: Scanner(shared.value))


def digest(names: Iterable) -> str:
    return hashlib.sha256(",".join(sorted({x for x in names if x is not None})).encode()).hexdigest()


def contamination(docs: DataFrame, bench: DataFrame, size: int = 10, max_nodes: int = MAX_NODES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated for each row."""
    schema = "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean"
    with Scratch(docs.sparkSession) as keep:
        found = keep(benchmark_windows(bench, size), "windows")
        blocks = blocks_of(found, max_nodes)
        if blocks == 1:
            scanner = shipped(found, 0, 1)

            def make():
                scan = scanner().scan

                def rows(ids, texts):
                    out = []
                    for i, t in zip(ids, texts, strict=True):
                        n, hit, seen = scan(t)
                        k = 0 if hit is None else int(hit.sum())
                        out.append((i, n, k, len(seen), digest(seen), k > 0))
                    return out

                return rows

            return map_texts(docs, [id_col, text_col], make, schema)
        return stored(many_passes(docs, found, blocks, schema, keep, id_col, text_col), "contamination")


def many_passes(docs: DataFrame, found: DataFrame, blocks: int, schema: str, keep: Scratch, id_col: str, text_col: str) -> DataFrame:
    """One pass for each block; each writes the hit stretches and items of its rows, which then meet by row."""
    d = keep(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"), F.monotonically_increasing_id().alias("row")), "documents")
    hits = None
    for block in range(blocks):
        scanner = shipped(found, block, blocks)

        def make(scanner=scanner):
            scan = scanner().scan

            def rows(numbers, texts):
                out = []
                for row, t in zip(numbers, texts, strict=True):
                    _, hit, seen = scan(t)
                    if hit is not None:
                        edge = np.flatnonzero(np.diff(np.concatenate([[0], hit.view(np.int8), [0]])))
                        out.append((row, edge.tolist(), [x for x in seen if x is not None], None in seen))
                return out

            return rows

        part = keep(map_texts(d, ["row", "text"], make, "row long, edges array<long>, items array<string>, nameless boolean"), "hits")
        hits = part if hits is None else hits.unionByName(part)
    hits = hits.groupBy("row").agg(F.collect_list("edges").alias("edges"), F.array_distinct(F.flatten(F.collect_list("items"))).alias("items"), F.bool_or("nameless").alias("nameless"))

    def last():
        def rows(ids, texts, edges, items, nameless):
            out = []
            for i, t, parts, names, none in zip(ids, texts, edges, items, nameless, strict=True):
                n = len(normal_words(t))
                flags = np.zeros(n + 1, np.int64)
                for e in parts or []:
                    flags[e[::2]] += 1
                    flags[e[1::2]] -= 1
                k = int((np.cumsum(flags)[:-1] > 0).sum())
                out.append((i, n, k, len(names or []) + bool(none), digest(names or []), k > 0))
            return out

        return rows

    return map_texts(d.join(hits.hint("merge"), "row", "left"), ["doc_id", "text", "edges", "items", "nameless"], last, schema)


def drop_contaminated(docs: DataFrame, bench: DataFrame, size: int = 10, max_nodes: int = MAX_NODES, text_col: str = "text") -> DataFrame:
    """Rows without any hit word, all columns untouched."""
    with Scratch(docs.sparkSession) as keep:
        found = keep(benchmark_windows(bench, size), "windows")
        blocks = blocks_of(found, max_nodes)
        for block in range(blocks):
            scanner = shipped(found, block, blocks)

            def make(scanner=scanner):
                scan = scanner().scan
                return lambda texts: [scan(t)[1] is None for t in texts]

            docs = filter_rows(docs, [text_col], make)
            if block < blocks - 1:  # one automaton at a time in a worker
                docs = keep(docs, "clean")
        return docs if blocks == 1 else stored(docs, "clean")
