"""Static range asymmetric numeral system over token ids: segments of independent interleaved blocks.

A segment is one self-contained byte string:

    header  magic 'RTS2', scale bits, documents, tokens, symbols, blocks, checkpoint rows (little-endian 32/64 bit)
    tables  zstandard-packed: document ids, document lengths, symbols and their normalised frequencies; with crc32
    index   for each block: tokens, lanes, checkpoints, words, byte offset, crc32 of its bytes
    blocks  for each block: lane states at its start and at each checkpoint with the word offset there, then words

All blocks of a segment share one frequency table. A block deals its tokens to lanes round robin; every lane keeps
a 63-bit state and spills 32-bit words into one stream in decoding order, so a row of lanes is one numpy step.
Decoding may begin at any block, and inside a block at any checkpoint; each block is checked by its crc32,
and a decoder that reaches a block's end checks that every lane is back in its first state and no word is left over.
"""

from __future__ import annotations

import struct
import zlib
from dataclasses import dataclass

import numpy as np

MAGIC = b"RTS2"
HEADER = struct.Struct("<4sIQQIII")
TABLES = struct.Struct("<IIIIII")
INDEX = struct.Struct("<IIIIQI")
LOW = np.uint64(1 << 31)
WORD = np.uint64(32)


@dataclass(frozen=True)
class RansConfig:
    block_tokens: int = 524_288
    lanes: int = 2048
    #: Rows of lanes between two checkpoints of a block.
    checkpoint_rows: int = 128
    level: int = 3


def normalised(counts: np.ndarray, bits: int) -> np.ndarray:
    """Frequencies of at least 1 that sum to 2**bits, in proportion to the counts."""
    total = 1 << bits
    f = np.maximum(1, counts.astype(np.float64) * (total / counts.sum())).astype(np.int64)
    rest = total - int(f.sum())
    if rest > 0:
        f[int(np.argmax(f))] += rest
    order = np.argsort(-f, kind="stable")
    at = 0
    while rest < 0:
        k = order[at % len(order)]
        take = min(-rest, max(0, int(f[k]) - 1), max(1, int(f[k]) // 8))
        f[k] -= take
        rest += take
        at += 1
    return f


def lanes_for(n: int, most: int) -> int:
    """A power of two so that a lane holds about 32 tokens at least."""
    return max(1, min(most, 1 << max(0, (n // 32).bit_length() - 1)))


def encode_block(symbols: np.ndarray, freq: np.ndarray, cum: np.ndarray, bits: int, cfg: RansConfig) -> tuple[int, int, int, bytes]:
    """(lanes, checkpoints, words, bytes) of one block of symbol numbers."""
    n = len(symbols)
    w = lanes_for(n, cfg.lanes)
    rows = -(-n // w)
    f, c = freq[symbols], cum[symbols]
    top = f << np.uint64(63 - bits)
    k = np.uint64(bits)
    x = np.full(w, LOW, np.uint64)
    out: list[np.ndarray] = []
    marks: list[tuple[int, np.ndarray]] = []  # rows from the end
    spilled = 0
    for r in range(rows - 1, -1, -1):
        a, b = r * w, min(n, (r + 1) * w)
        xs, fs = x[: b - a], f[a:b]
        full = xs >= top[a:b]
        if full.any():
            spill = xs[full]
            out.append(spill.astype(np.uint32))
            spilled += len(spill)
            xs = np.where(full, xs >> WORD, xs)
        q = xs // fs
        x[: b - a] = (q << k) + (xs - q * fs) + c[a:b]
        if r and r % cfg.checkpoint_rows == 0:
            marks.append((spilled, x.copy()))
    words = np.concatenate(out[::-1]) if out else np.zeros(0, np.uint32)
    body = [x.astype("<u8").tobytes()]
    for before_end, state in marks[::-1]:
        body += [struct.pack("<Q", len(words) - before_end), state.astype("<u8").tobytes()]
    return w, len(marks), len(words), b"".join([*body, words.astype("<u4").tobytes()])


def decode_rows(x: np.ndarray, words: np.ndarray, at: int, n: int, tables: tuple, bits: int) -> np.ndarray:
    """The last ``n`` symbol numbers of a block from lane states ``x`` and the words from ``at`` on."""
    slot_symbol, freq, cum = tables
    w, out = len(x), np.empty(n, np.uint32)
    k, mask = np.uint64(bits), np.uint64((1 << bits) - 1)
    for a in range(0, n, w):
        b = min(n, a + w)
        xs = x[: b - a]
        slot = xs & mask
        s = slot_symbol[slot]
        out[a:b] = s
        xs = freq[s] * (xs >> k) + slot - cum[s]
        low = xs < LOW
        m = int(np.count_nonzero(low))
        if m:
            xs[low] = (xs[low] << WORD) | words[at : at + m].astype(np.uint64)
            at += m
        x[: b - a] = xs
    if at != len(words) or (x != LOW).any():
        raise ValueError("the block does not end where its tokens do")
    return out


def pack(a: np.ndarray, dtype: str, z) -> bytes:
    return z.compress(np.ascontiguousarray(a.astype(dtype)).tobytes())


def encode_segment(doc_ids: list[int | None], lengths: np.ndarray, ids: np.ndarray, cfg: RansConfig = RansConfig()) -> bytes:
    """Bytes of one segment; ``ids`` are the tokens of all its documents in order."""
    import zstandard

    z = zstandard.ZstdCompressor(level=cfg.level)
    lengths = np.asarray(lengths, np.int64)
    known, counts = np.unique(ids, return_counts=True) if len(ids) else (np.zeros(0, np.uint32), np.zeros(0, np.int64))
    bits = max(14, min(24, int(len(known)).bit_length() + 3))
    blocks = []
    if len(known):
        freq = normalised(counts, bits)
        cum = np.concatenate([[0], np.cumsum(freq)[:-1]]).astype(np.uint64)
        number = np.zeros(int(known[-1]) + 1, np.uint32)
        number[known] = np.arange(len(known), dtype=np.uint32)
        symbols, f64 = number[ids], freq.astype(np.uint64)
        for a in range(0, len(symbols), cfg.block_tokens):
            part = symbols[a : a + cfg.block_tokens]
            blocks.append((len(part), *encode_block(part, f64, cum, bits, cfg)))
    else:
        freq = np.zeros(0, np.int64)
    has = np.array([i is not None for i in doc_ids], bool)
    values = np.array([0 if i is None else i for i in doc_ids], np.int64)
    with np.errstate(over="ignore"):
        packed = [
            z.compress(np.packbits(has).tobytes()),
            pack(np.diff(values, prepend=np.int64(0)), "<i8", z),
            pack(lengths, "<u8", z),
            pack(np.diff(known.astype(np.int64), prepend=0), "<u4", z),
            pack(freq, "<u4", z),
        ]
    tables = b"".join(packed)
    index, offset = [], 0
    for n, w, marks, words, body in blocks:
        index.append(INDEX.pack(n, w, marks, words, offset, zlib.crc32(body)))
        offset += len(body)
    head = HEADER.pack(MAGIC, bits, len(doc_ids), len(ids), len(known), len(blocks), cfg.checkpoint_rows)
    lens = TABLES.pack(*(len(p) for p in packed), zlib.crc32(head + tables + b"".join(index)))
    return b"".join([head, lens, tables, *index, *(b[-1] for b in blocks)])


class Segment:
    """A parsed segment; blocks decode independently, whatever settings it was written with."""

    def __init__(self, blob: bytes):
        import zstandard

        z = zstandard.ZstdDecompressor()
        magic, self.bits, n_docs, self.n_tokens, n_symbols, n_blocks, self.checkpoint_rows = HEADER.unpack_from(blob)
        if magic != MAGIC:
            raise ValueError("not a token segment")
        *sizes, crc = TABLES.unpack_from(blob, HEADER.size)
        at = HEADER.size + TABLES.size
        end = at + sum(sizes) + INDEX.size * n_blocks
        if zlib.crc32(blob[: HEADER.size] + blob[at:end]) != crc:
            raise ValueError("segment tables are damaged")
        parts = []
        for s in sizes:
            parts.append(z.decompress(blob[at : at + s]))
            at += s
        has = np.unpackbits(np.frombuffer(parts[0], np.uint8), count=n_docs).astype(bool)
        with np.errstate(over="ignore"):
            values = np.cumsum(np.frombuffer(parts[1], "<i8"))
        self.doc_ids = [int(v) if h else None for v, h in zip(values, has, strict=True)]
        self.lengths = np.frombuffer(parts[2], "<u8").astype(np.int64)
        self.known = np.cumsum(np.frombuffer(parts[3], "<u4").astype(np.int64)).astype(np.uint32)
        freq = np.frombuffer(parts[4], "<u4").astype(np.int64)
        self.blocks = [INDEX.unpack_from(blob, at + INDEX.size * i) for i in range(n_blocks)]
        self.base, self.blob = end, blob
        cum = np.concatenate([[0], np.cumsum(freq)[:-1]]) if n_symbols else freq
        self.tables = (np.repeat(np.arange(n_symbols, dtype=np.uint32), freq), freq.astype(np.uint64), cum.astype(np.uint64))

    def block(self, b: int, checkpoint: int = 0) -> np.ndarray:
        """Token ids of block ``b`` from its ``checkpoint``-th checkpoint on (0: its start)."""
        n, w, marks, n_words, offset, crc = self.blocks[b]
        size = 8 * w * (marks + 1) + 8 * marks + 4 * n_words
        body = self.blob[self.base + offset : self.base + offset + size]
        if zlib.crc32(body) != crc:
            raise ValueError(f"block {b} is damaged")
        words = np.frombuffer(body, "<u4", n_words, size - 4 * n_words)
        if checkpoint:
            where = 8 * w * checkpoint + 8 * (checkpoint - 1)
            at, x = struct.unpack_from("<Q", body, where)[0], np.frombuffer(body, "<u8", w, where + 8)
        else:
            at, x = 0, np.frombuffer(body, "<u8", w, 0)
        left = n - checkpoint * self.checkpoint_rows * w
        return self.known[decode_rows(x.astype(np.uint64), words, at, left, self.tables, self.bits)]

    def ids(self) -> np.ndarray:
        return np.concatenate([self.block(b) for b in range(len(self.blocks))]) if self.blocks else np.zeros(0, np.uint32)
