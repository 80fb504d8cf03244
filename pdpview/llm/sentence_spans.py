"""Substring deduplication by sliding spans of sentences.

A sentence ends at ``.``, ``!`` or ``?`` before white space, or at a line end. At every sentence a span begins: it runs
over consecutive sentences until it has ``sentences`` of them and ``least_words`` words. Spans are hashed to 128 bits
over their lower-cased words. A span's first occurrence is in the document with the smallest id, at its earliest place
there; sentences under any other occurrence are cut.

Parameter ``long``: a sentence of more words is cut after words that their hash picks (about every sixth), and its
pieces count as sentences. Text without marks, and a passage pasted into the middle of a sentence, so still hold
complete runs; 0 turns it off.

All spans of all documents meet by hash: a partial aggregate gives each hash its first document and keeps hashes
that occur again, and a join (which Spark splits when one hash is hot) finds the later occurrences.

Edge cases: null texts stay null, empty ones empty; documents without a complete span keep all; equal ids are one
document (their rows are not repeats of each other, each row is cut alike); null ids count as one document that
comes first; an empty table gives no rows; extra columns are not read.
"""

from __future__ import annotations

import re
import struct
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .texts import map_texts, words_of

SENTENCE_END = re.compile(r"(?<=[.!?])[\x20\x09-\x0D]+|\n[\x20\x09-\x0D]*")

ANY_WORD = re.compile(r"\S+")  # what str.split gives

#: Stands for a null id; it comes before all ids.
NO_ID = -(1 << 63)


@dataclass(frozen=True)
class SpanConfig:
    sentences: int = 2
    least_words: int = 12
    #: Longer sentences are cut at about every sixth word (0: none).
    long: int = 16


def sentence_bounds(text: str) -> list[tuple[int, int]]:
    """(begin, end) of each sentence; the white space after a sentence belongs to it."""
    out, at = [], 0
    for m in SENTENCE_END.finditer(text):
        if m.end() > at:
            out.append((at, m.end()))
            at = m.end()
    if at < len(text):
        out.append((at, len(text)))
    return out


_ENDS: dict[str, bool] = {}


def ends_piece(word: str) -> bool:
    """Whether a long sentence is cut after this lower-cased word: by the word's own hash, so alike anywhere."""
    end = _ENDS.get(word)
    if end is None:
        if len(_ENDS) >= 200_000:
            _ENDS.clear()
        end = _ENDS[word] = crc32(word.encode("utf-8", "replace")) % 6 == 0
    return end


def cut_long(text: str, a: int, b: int) -> list[tuple[int, int]]:
    """Bounds of the pieces of a long sentence."""
    out, at, last = [], a, False
    for m in ANY_WORD.finditer(text, a, b):
        if last:
            out.append((at, m.start()))
            at = m.start()
        last = ends_piece(m[0].lower())
    return [*out, (at, b)]


def units(text: str, cfg: SpanConfig) -> list[tuple[int, int, str, int]]:
    """(begin, end, lower-cased words in one string, number of words) of each sentence."""
    out = []
    for a, b in sentence_bounds(text):
        words = text[a:b].lower().split()
        if not cfg.long or len(words) <= cfg.long:
            out.append((a, b, " ".join(words), len(words)))
        else:
            for x, y in cut_long(text, a, b):
                words = text[x:y].lower().split()
                out.append((x, y, " ".join(words), len(words)))
    return out


def spans(text: str | None, cfg: SpanConfig) -> tuple[list[tuple[int, int]], list[tuple[bytes, int, int]]]:
    """Sentence bounds, and (hash of 16 bytes, first sentence, end sentence) of each complete span."""
    from xxhash import xxh3_128_digest

    if not text:
        return [], []
    u = units(text, cfg)
    norm, count = [x[2] for x in u], [x[3] for x in u]
    out, j, total, used = [], 0, 0, 0  # sentences i..j-1 hold ``total`` words, ``used`` of them are not empty
    n, least, few = len(u), cfg.least_words, cfg.sentences
    for i in range(n):
        while j < n and (used < few or total < least):
            total += count[j]
            used += count[j] > 0
            j += 1
        if used < few or total < least:
            break
        if count[i]:
            out.append((xxh3_128_digest(" ".join(filter(None, norm[i:j]))), i, j))
            total -= count[i]
            used -= 1
    return [x[:2] for x in u], out


def span_hashes(text: str | None, cfg: SpanConfig) -> list[bytes]:
    """The hashes of ``spans`` alone, without places."""
    from xxhash import xxh3_128_digest

    if not text:
        return []
    norm, count = [], []
    for sentence in SENTENCE_END.split(text):
        words = sentence.lower().split()
        if not words:
            continue
        if not cfg.long or len(words) <= cfg.long:
            norm.append(" ".join(words))
            count.append(len(words))
            continue
        at = 0
        for k in [k for k, w in enumerate(words, 1) if ends_piece(w)]:
            norm.append(" ".join(words[at:k]))
            count.append(k - at)
            at = k
        if at < len(words):
            norm.append(" ".join(words[at:]))
            count.append(len(words) - at)
    out, j, total, n, least, few = [], 0, 0, len(norm), cfg.least_words, cfg.sentences
    for i in range(n):
        while j < n and (j - i < few or total < least):
            total += count[j]
            j += 1
        if j - i < few or total < least:
            break
        out.append(xxh3_128_digest(" ".join(norm[i:j])))
        total -= count[i]
    return out


def repeated_spans(docs: DataFrame, cfg: SpanConfig = SpanConfig(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc, hits: hashes of each document's spans that occur in an earlier document (``whole``) or earlier in this one."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                digests: list[bytes] = []
                again: list[bool] = []
                sizes = []
                for t in part.column(1).to_pylist():
                    times = Counter(span_hashes(t, cfg))  # a span goes out once for each document
                    digests += times.keys()
                    again += [k > 1 for k in times.values()]
                    sizes.append(len(times))
                h = np.frombuffer(b"".join(digests), ">i8").astype(np.int64).reshape(-1, 2)
                ids = pa.array(np.repeat(np.arange(len(sizes)), sizes))
                cols = [pa.array(np.ascontiguousarray(h[:, 0])), pa.array(np.ascontiguousarray(h[:, 1])), part.column(0).cast(pa.int64()).take(ids), pa.array(again, pa.bool_())]
                yield pa.RecordBatch.from_arrays(cols, names=["hi", "lo", "doc_id", "again"])

    found = docs.select(id_col, text_col).mapInArrow(run, "hi long, lo long, doc_id long, again boolean")
    found = found.withColumn("doc", F.coalesce("doc_id", F.lit(NO_ID)))
    first = found.groupBy("hi", "lo").agg(F.min("doc").alias("first"), F.max("doc").alias("last"), F.max("again").alias("twice")).filter("first < last OR twice")
    later = found.join(first.select("hi", "lo", "first").hint("merge"), ["hi", "lo"]).filter("doc > first OR again")
    return later.groupBy("doc").agg(F.collect_set(F.struct("hi", "lo", (F.col("doc") > F.col("first")).alias("whole"))).alias("hits"))


def remove_repeats(docs: DataFrame, cfg: SpanConfig = SpanConfig(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_removed (sentences), removed_words, removed (character spans), text without them."""
    hits = repeated_spans(docs, cfg, id_col, text_col)
    d = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    d = d.withColumn("doc", F.coalesce("doc_id", F.lit(NO_ID))).join(hits.hint("merge"), "doc", "left")

    def make():
        def rows(ids, texts, hits):
            out = []
            for i, t, h in zip(ids, texts, hits, strict=True):
                if not h:
                    out.append((i, 0, 0, [], t))
                    continue
                known = {struct.pack(">qq", x["hi"], x["lo"]): x["whole"] for x in h}
                bounds, own = spans(t, cfg)
                gone = [False] * len(bounds)
                seen = set()
                for x, a, b in own:
                    if x in known:
                        if known[x] or x in seen:  # the first occurrence of all is in this document: it stays
                            gone[a:b] = [True] * (b - a)
                        seen.add(x)
                cut, kept, words = [], [], 0
                for (a, b), g in zip(bounds, gone, strict=True):
                    if not g:
                        kept.append(t[a:b])
                        continue
                    words += len(words_of(t[a:b]))
                    if cut and cut[-1][1] == a:
                        cut[-1] = (cut[-1][0], b)
                    else:
                        cut.append((a, b))
                out.append((i, sum(gone), words, [{"begin": a, "end": b} for a, b in cut], "".join(kept) if t else t))
            return out

        return rows

    schema = "doc_id long, n_removed long, removed_words long, removed array<struct<begin:long,end:long>>, text string"
    return map_texts(d, ["doc_id", "text", "hits"], make, schema, rows=128)
