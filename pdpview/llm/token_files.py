"""Token-id files: whole texts to ids, ids to range-coded segments in document order, segments back to documents.

Documents are range-partitioned and sorted by id; each task tokenises its range and emits segments of about
``segment_tokens`` tokens (see ``rans``), as rows of a Parquet dataset, Spark's writer giving atomic, retried
output on any file system. A segment's place among all tokens follows from the segments' sizes alone.

Edge cases: null and empty texts hold the end id only; null ids sort first and stay null; repeated ids are kept,
ordered by text; an empty table gives no segments; a text longer than a segment simply makes its segment longer.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from itertools import islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .bpe_count import byte_alphabet
from .rans import RansConfig, Segment, encode_segment
from .texts import give_back, map_texts, per_worker, stored

SEGMENT_SCHEMA = "shard int, seg int, n_docs long, n_tokens long, bytes binary"


class Encoder:
    """Whole texts to ids through the library, each different piece of a column once.

    Pretokens never cross the place before a space that a non-space follows, so texts are cut at spaces, in Arrow, and
    only the column's different pieces are encoded. Texts with a special string, or with a space before other white
    space or the end, go to the library whole.
    """

    def __init__(self, spec: str, end_id: int):
        import re

        from tokenizers import Tokenizer

        self.tokenizer, self.end = Tokenizer.from_str(spec), end_id
        added = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        alphabet = {c: b for b, c in byte_alphabet().items()}
        vocab = self.tokenizer.get_vocab()
        self.bytes_of = np.zeros(max(vocab.values(), default=0) + 1, np.int64)
        for token, i in vocab.items():
            self.bytes_of[i] = len(token) if all(c in alphabet for c in token) else 0
        #: What keeps a text from being cut: special strings; a space before any white space or the end.
        self.odd = "|".join([*map(re.escape, added), r" (?:[\s\v\x1c-\x1f\x{85}\x{a0}\x{1680}\x{180e}\x{2000}-\x{200d}\x{2028}\x{2029}\x{202f}\x{205f}\x{2060}\x{3000}\x{feff}]|\z)"])

    def whole(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(e.ids, np.uint32) for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def pieces(self, pieces: pa.Array) -> tuple[list[np.ndarray], np.ndarray]:
        """Ids of " " + piece, of all pieces in parts, and the number of ids of each piece.

        Some thousand pieces are encoded as one text and cut again where their bytes end.
        """
        import pyarrow.compute as pc

        ids, sizes = [], []
        for a in range(0, len(pieces), 2_000):
            part = pieces.slice(a, 2_000)
            lists = pa.ListArray.from_arrays(pa.array([0, len(part)], pa.int32()), part)
            text = " " + pc.binary_join(lists, " ")[0].as_py()
            got = np.array(self.tokenizer.encode_batch_fast([text], add_special_tokens=False)[0].ids, np.uint32)
            ends = np.cumsum(pc.binary_length(part).to_numpy().astype(np.int64) + 1)
            at = np.cumsum(self.bytes_of[got])
            stop = np.searchsorted(at, ends) + 1
            if len(at) != stop[-1] or (at[stop - 1] != ends).any():
                raise ValueError("tokens cross the pieces; this vocabulary is not byte-level")
            ids.append(got)
            sizes.append(np.diff(stop, prepend=0))
        return ids, np.concatenate(sizes) if sizes else np.zeros(0, np.int64)

    def encode(self, texts: pa.Array, docs: int = 1024) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """For each ``docs`` texts in turn: their ids one after another, each with the end id; ids of each text."""
        import pyarrow.compute as pc

        n = len(texts)
        texts = pc.fill_null(texts, "")
        odd = np.flatnonzero(pc.match_substring_regex(texts, self.odd).to_numpy(zero_copy_only=False))
        if len(odd):
            rest = self.whole(texts.take(pa.array(odd)).to_pylist())
            flags = np.zeros(n, bool)
            flags[odd] = True
            texts = pc.if_else(pa.array(flags), "", texts)
        lists = pc.split_pattern(texts, " ")
        offsets = lists.offsets.to_numpy().astype(np.int64)
        values = lists.values.slice(offsets[0], offsets[-1] - offsets[0])
        offsets = offsets - offsets[0]
        heads = self.whole(values.take(pa.array(offsets[:-1])).to_pylist())  # no space stands before a text's first piece
        for k, i in enumerate(odd.tolist()):
            heads[i] = rest[k]
        coded = values.dictionary_encode()
        known, size = self.pieces(coded.dictionary)
        codes = coded.indices.to_numpy()
        n_known = len(size)
        flat = np.concatenate([*known, *heads, np.array([self.end], np.uint32)])
        size = np.concatenate([size, np.fromiter(map(len, heads), np.int64, n), [1]])
        start = np.cumsum(size) - size
        for a in range(0, n, docs):
            # table entries in reading order: a text's head, its other pieces, the end id
            b = min(n, a + docs)
            at = offsets[a : b + 1] - offsets[a]
            k = np.arange(b - a)
            code = np.empty(at[-1] + b - a, np.int64)
            code[np.arange(at[-1]) + np.repeat(k, np.diff(at))] = codes[offsets[a] : offsets[b]]
            code[at[:-1] + k] = n_known + a + k
            code[at[1:] + k] = len(size) - 1
            lengths = size[code]
            ends = np.cumsum(lengths)
            yield flat[np.repeat(start[code] - (ends - lengths), lengths) + np.arange(ends[-1])], np.add.reduceat(lengths, at[:-1] + k)


def encode_segments(docs: DataFrame, tokenizer_path: str, end_id: int = 0, segment_tokens: int = 2_000_000, cfg: RansConfig = RansConfig(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (shard, seg, n_docs, n_tokens, bytes) in document order; shards are consecutive id ranges."""
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    with open(tokenizer_path, encoding="utf-8") as f:
        shared = docs.sparkSession.sparkContext.broadcast(f.read())
    d = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    d = d.repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import os

        from pyspark import TaskContext

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        encoder = per_worker("encoder", tokenizer_path, lambda: Encoder(shared.value, end_id))
        shard, seg = TaskContext.get().partitionId(), 0
        ids: list[int | None] = []
        parts: list[np.ndarray] = []
        sizes: list[np.ndarray] = []
        held = 0

        def flush() -> pa.RecordBatch:
            lengths = np.concatenate(sizes)
            blob = encode_segment(ids, lengths, np.concatenate(parts), cfg)
            cols = ([shard], [seg], [len(ids)], [int(lengths.sum())], [blob])
            types = (pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.binary())
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names=["shard", "seg", "n_docs", "n_tokens", "bytes"])

        for batch in batches:
            names = iter(batch.column(0).to_pylist())
            for tokens, lengths in encoder.encode(batch.column(1)):
                ids += islice(names, len(lengths))
                parts.append(tokens)
                sizes.append(lengths)
                held += len(tokens)
                if held >= segment_tokens:
                    yield flush()
                    ids, parts, sizes, held, seg = [], [], [], 0, seg + 1
        if ids:
            yield flush()
        ids, parts, sizes = [], [], []
        give_back()

    return d.mapInArrow(run, SEGMENT_SCHEMA)


def starts(segments: DataFrame) -> DataFrame:
    """shard, seg, base: tokens before each segment. Reads sizes only; one row for each shard meets in one task."""
    sizes = segments.select("shard", "seg", "n_tokens")
    shard = sizes.groupBy("shard").agg(F.sum("n_tokens").alias("all"))
    shard = shard.select("shard", (F.sum("all").over(Window.orderBy("shard")) - F.col("all")).alias("before"))
    inside = Window.partitionBy("shard").orderBy("seg").rowsBetween(Window.unboundedPreceding, -1)
    return sizes.withColumn("inside", F.coalesce(F.sum("n_tokens").over(inside), F.lit(0))).join(shard, "shard").select("shard", "seg", (F.col("before") + F.col("inside")).alias("base"))


def read_documents(segments: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of each document, decoded from the segments."""

    def make():
        def rows(shards, segs, blobs):
            out = []
            for shard, seg, blob in zip(shards, segs, blobs, strict=True):
                s = Segment(blob)
                raw = memoryview(s.ids().astype("<u4").tobytes())
                at = 0
                for i, n in zip(s.doc_ids, s.lengths.tolist(), strict=True):
                    out.append((shard, seg, i, at, n, zlib.crc32(raw[4 * at : 4 * (at + n)])))
                    at += n
            return out

        return rows

    decoded = map_texts(segments, ["shard", "seg", "bytes"], make, "shard int, seg int, doc_id long, at long, n_tokens long, ids_crc32 long", rows=1)
    return decoded.join(starts(segments), ["shard", "seg"]).select("doc_id", (F.col("base") + F.col("at")).alias("start"), "n_tokens", "ids_crc32")


def round_trip(docs: DataFrame, tokenizer_path: str, **how) -> DataFrame:
    """Writes the token files of ``docs`` to the shared folder and reads every document back from them."""
    return read_documents(stored(encode_segments(docs, tokenizer_path, **how), "tokens"))
