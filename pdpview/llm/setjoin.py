"""Exact Jaccard self-join on word shingles with set-relation skipping, and the components of its links.

Sets: distinct 5-word shingles as 64-bit hashes. Documents with equal sets are one node. The join runs in steps:

1. Shared shingles. Each task packs its sets' hashes by hash range into compact sorted blocks; one task for each
   range finds the shingles that two or more different sets hold, with their frequencies. Only those go on. A shingle
   that is frequent already inside a pack sends its count there and its sets elsewhere, dealt out by pack, so that no
   task meets all sets of a hot shingle; a join brings the frequencies back, one row for each pack and shingle, and
   the pack tells its sets.
2. Index. A set needs 80 % of its shingles shared to have any partner; others leave. A set's shared shingles are
   ordered from rare to frequent (its private ones come before all), and by the prefix principle two sets can only
   link if they meet in the index list of one of their first n - ceil(0.8 n) + 1 shingles.
3. Centres. In every index list all sets are compared with the list's centre (the set with the fewest private
   shingles), then with a random one. Linked sets share a component, so within a list only pairs whose components
   still differ are of interest: whole lists and all pairs inside a component are skipped.
4. Answers from similar sets, for left-over sets of long lists. The centre's answers are known, and a set's answers
   follow from how the set differs from the centre: two sets whose differences from it have d1 and d2 shingles differ
   in d1 + d2 less twice what the differences share, so to link they must share a known number of differing shingles.
   Those are indexed instead of the sets. They are ordered by how many members differ in them, members are cut into
   blocks by the size of their difference, and a list of differing shingles is split by pairs of blocks: a member is
   in it only if its place (differing shingles from there on) lets it meet that block's bound; else the block is skipped.
   So a group of G near copies with U members that link to nothing costs about G, not U x G.
   Lists of up to ``short`` sets are one block: their left-over pairs pass by position (the places of the meeting
   shingle bound the overlap), size, and a parity bitmap that bounds the symmetric difference from below.
What passes is verified exactly. No list or candidate is capped.

Components come from minimum labels: each round jumps one pointer and lowers nodes and the nodes their labels name, until
nothing moves (12 rounds on chains of 2,000 in random order); each round is written to the shared folder.

Edge cases: documents of fewer than five words are one shingle; null, empty and wordless ones have no shingle and
are alone; repeated rows and equal ids are one node each if their sets are equal; a component's id is the smallest
id in it (null only if all its ids are null); an empty table gives no rows; extra columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .texts import Scratch, give_back, hot_keys, lookup, stored

#: A-Z to a-z in UTF-8 bytes.
LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
MIX = np.uint64(0x9E3779B97F4A7C15)
BITMAP_WORDS = 16
#: In packs for hash ranges, values from here on stand for counts, not for sets; fingerprints never fall there.
COUNT, COUNT_RANGE = -(1 << 63), 1 << 40


@dataclass(frozen=True)
class JoinConfig:
    words: int = 5
    #: Links need 100 * intersection >= percent * union.
    percent: int = 80
    #: Hashes that a task packs at a time.
    pack: int = 500_000
    #: Hash ranges for each shuffle partition.
    ranges: int = 6
    #: Texts that are split at a time.
    texts: int = 256
    #: A shingle in so many different sets of one pack is counted there; its sets do not go to its range's task.
    heavy: int = 16
    #: Rounds of comparing index lists with one set.
    rounds: int = 2
    #: Lists of so many sets are one block: left-over pairs are formed directly. Longer ones go by differences.
    short: int = 32
    #: A block of members spans differences of one shingle, or of this part of their centre's shingles.
    blocks: int = 128


def finish(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(33))) * np.uint64(0xFF51AFD7ED558CCD)
    h = (h ^ (h >> np.uint64(33))) * np.uint64(0xC4CEB9FE1A85EC53)
    return h ^ (h >> np.uint64(33))


class Shingler:
    """Sorted distinct shingle hashes of whole texts, a column at a time: words are split and numbered in Arrow, each
    different word is hashed once."""

    def __init__(self, size: int):
        import xxhash

        self.size, self.hash = size, xxhash.xxh3_64_intdigest

    def sets(self, texts: pa.Array) -> list[np.ndarray]:
        import pyarrow.compute as pc

        # the six ASCII separators are Arrow's ASCII white space; a text that begins or ends with one gives an empty piece
        lists = pc.ascii_split_whitespace(pc.ascii_lower(pc.fill_null(texts, "")))
        offsets = lists.offsets.to_numpy().astype(np.int64)
        values = lists.values.slice(offsets[0], offsets[-1] - offsets[0])
        offsets = offsets - offsets[0]
        coded = values.dictionary_encode()
        words = coded.dictionary.cast(pa.binary()).to_pylist()
        table = np.fromiter(map(self.hash, words), np.uint64, len(words))
        code = coded.indices.to_numpy()
        real = pc.binary_length(values).to_numpy() > 0
        ends = np.concatenate([[0], np.cumsum(real)])[offsets]
        h = table[code[real]]
        k = self.size
        rolled = np.zeros(max(0, len(h) - k + 1), np.uint64)
        for i in range(k):
            rolled = rolled * MIX + h[i : len(h) - k + 1 + i] if len(rolled) else rolled
        rolled = finish(rolled + np.uint64(k))
        out = []
        for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True):
            if b - a >= k:
                out.append(np.unique(rolled[a : b - k + 1]))
            elif b > a:
                s = np.zeros(1, np.uint64)
                for x in h[a:b]:
                    s = s * MIX + x
                out.append(finish(s + np.uint64(b - a)))
            else:
                out.append(np.zeros(0, np.uint64))
        return out


def fingerprint(s: np.ndarray) -> int:
    """64-bit identity of a set: an order-free sum of mixed hashes."""
    x = (int(finish(s ^ np.uint64(0xD6E8FEB86659FD93)).sum()) + len(s) * int(MIX)) & (1 << 64) - 1
    x = x - (1 << 64) if x >> 63 else x
    return x if x >= COUNT + COUNT_RANGE else x + COUNT_RANGE  # keeps clear of the counts


def document_sets(docs: DataFrame, cfg: JoinConfig, id_col: str, text_col: str) -> DataFrame:
    """doc_id, n, fp, text_hash of each row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sh = Shingler(cfg.words)
        for batch in batches:
            for at in range(0, batch.num_rows, cfg.texts):
                part = batch.slice(at, cfg.texts)
                sets = sh.sets(part.column(1))
                cols = [part.column(0).cast(pa.int64()), pa.array([len(s) for s in sets], pa.int64()), pa.array([fingerprint(s) if len(s) else None for s in sets], pa.int64()), part.column(2)]
                yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "n", "fp", "text_hash"])
        give_back()

    return docs.select(id_col, text_col, F.xxhash64(text_col)).mapInArrow(run, "doc_id long, n long, fp long, text_hash long")


def pack(h: np.ndarray, owner: np.ndarray) -> bytes:
    """Sorted hashes as differences, and owners, in byte planes under zstandard."""
    import zstandard

    d = np.diff(h, prepend=np.uint64(0)).view(np.uint8).reshape(-1, 8).T
    o = owner.astype("<u4").view(np.uint8).reshape(-1, 4).T
    return zstandard.ZstdCompressor(level=1).compress(np.ascontiguousarray(d).tobytes() + np.ascontiguousarray(o).tobytes())


def unpack(raw: bytes, n: int) -> tuple[np.ndarray, np.ndarray]:
    import zstandard

    b = np.frombuffer(zstandard.ZstdDecompressor().decompress(raw), np.uint8)
    d = np.ascontiguousarray(b[: 8 * n].reshape(8, n).T).view("<u8").ravel()
    o = np.ascontiguousarray(b[8 * n :].reshape(4, n).T).view("<u4").ravel()
    return np.cumsum(d, dtype=np.uint64), o


def shared_shingles(docs: DataFrame, cfg: JoinConfig, text_col: str, keep: Scratch) -> DataFrame:
    """fp, x, often: the shingles (df, tok) that at least two different sets hold, for each set that holds them: one
    row with x for each shingle, but one row with the array ``often`` for all shingles that are frequent in a pack."""
    ranges = cfg.ranges * int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        sh = Shingler(cfg.words)
        sets: dict[int, np.ndarray] = {}
        held, packs, task = 0, 0, TaskContext.get().partitionId()
        schema = pa.schema([("p", pa.int32()), ("pack", pa.int64()), ("n", pa.int64()), ("fps", pa.binary()), ("packed", pa.binary())])

        def flush() -> pa.RecordBatch:
            fps = np.fromiter(sets.keys(), np.int64, len(sets))
            h = np.concatenate(list(sets.values()))
            owner = np.repeat(np.arange(len(fps)), [len(s) for s in sets.values()])
            order = np.argsort(h)
            h, owner = h[order], owner[order]
            first = np.flatnonzero(np.concatenate([[True], h[1:] != h[:-1]]))
            times = np.diff(np.append(first, len(h)))
            often = times >= cfg.heavy
            cols: tuple[list, ...] = ([], [], [], [], [])

            def put(p: int, h: np.ndarray, owner: np.ndarray, names: np.ndarray) -> None:
                used, local = np.unique(owner, return_inverse=True)
                for c, v in zip(cols, (p, (task << 32) + packs, len(h), names[used].tobytes(), pack(h, local)), strict=True):
                    c.append(v)

            if often.any():
                # sets of frequent shingles: packs are dealt out evenly, whatever the shingle
                of = np.repeat(often, times)
                put(ranges + (task + 7919 * packs) % ranges, h[of], owner[of], fps)
            # to the ranges: a frequent shingle once, with its count in place of a set (below COUNT); others with their sets
            light = ~np.repeat(often, times)
            names = np.concatenate([fps, COUNT + times[often]])
            h2 = np.concatenate([h[light], h[first[often]]])
            owner2 = np.concatenate([owner[light], len(fps) + np.arange(int(often.sum()))])
            order = np.argsort(h2, kind="stable")
            h2, owner2 = h2[order], owner2[order]
            at = np.searchsorted(h2, (np.arange(1, ranges, dtype=np.float64) * (2.0**64 / ranges)).astype(np.uint64))
            cuts = np.concatenate([[0], at, [len(h2)]])
            for p in range(ranges):
                a, b = int(cuts[p]), int(cuts[p + 1])
                if a < b:
                    put(p, h2[a:b], owner2[a:b], names)
            return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(cols, schema, strict=True)], schema=schema)

        for batch in batches:
            for at in range(0, batch.num_rows, cfg.texts):
                for s in sh.sets(batch.column(0).slice(at, cfg.texts)):
                    if len(s) and (fp := fingerprint(s)) not in sets:
                        sets[fp] = s
                        held += len(s)
                        if held >= cfg.pack:
                            yield flush()
                            sets, held, packs = {}, 0, packs + 1
        if sets:
            yield flush()
        sets = {}
        give_back()

    def meet(table: pa.Table) -> pa.Table:
        """Rows (fp, tok, df); fp is null where a frequent shingle's df stands. A pack of sets of frequent shingles goes
        on as it is, beside a row (pack, tok) for each of its shingles."""
        if table.column("p")[0].as_py() >= ranges:
            toks = [np.unique(unpack(raw, n)[0]) for n, raw in zip(*(table.column(c).to_pylist() for c in ("n", "packed")), strict=True)]
            give_back()
            names, none = np.repeat(table.column("pack").to_numpy(), [len(t) for t in toks]), lambda n: pa.nulls(n, pa.int64())
            asked = pa.table({"fp": none(len(names)), "tok": np.concatenate(toks).view(np.int64), "df": none(len(names)), "pack": names})
            gone = pa.table({k: none(len(table)) for k in ("fp", "tok", "df")} | {k: table.column(k) for k in ("pack", "n", "fps", "packed")})
            return pa.concat_tables([gone, asked], promote_options="default").select(gone.column_names)
        hs, fs = [], []
        for n, fps, raw in zip(*(table.column(c).to_pylist() for c in ("n", "fps", "packed")), strict=True):
            h, o = unpack(raw, n)
            hs.append(h)
            fs.append(np.frombuffer(fps, np.int64)[o])
        h, f = np.concatenate(hs), np.concatenate(fs)
        del hs, fs
        give_back()
        counted = (f >= COUNT) & (f < COUNT + COUNT_RANGE)
        order = np.argsort(h, kind="stable")
        h, f, counted = h[order], f[order], counted[order]
        same = h[1:] == h[:-1]
        keep = np.concatenate([same, [False]]) | np.concatenate([[False], same]) | counted
        h, f, counted = h[keep], f[keep], counted[keep]
        order = np.lexsort((f, h))  # the same set may come from several packs
        h, f, counted = h[order], f[order], counted[order]
        new = np.ones(len(h), bool)
        new[1:] = (h[1:] != h[:-1]) | (f[1:] != f[:-1]) | counted[1:]
        h, f, counted = h[new], f[new], counted[new]
        start = np.flatnonzero(np.concatenate([[True], h[1:] != h[:-1]])) if len(h) else np.zeros(0, np.int64)
        size = np.diff(np.append(start, len(h)))
        df = np.add.reduceat(np.where(counted, f - COUNT, 1), start) if len(h) else np.zeros(0, np.int64)
        frequent = np.add.reduceat(counted.astype(np.int64), start) > 0 if len(h) else np.zeros(0, bool)
        each = np.repeat(df, size)
        rows = ~counted & (each > 1)
        fp = pa.concat_arrays([pa.array(f[rows]), pa.nulls(int(frequent.sum()), pa.int64())])
        tok = np.concatenate([h[rows], h[start[frequent]]]).view(np.int64)
        none = {k: pa.nulls(len(fp), t) for k, t in (("pack", pa.int64()), ("n", pa.int64()), ("fps", pa.binary()), ("packed", pa.binary()))}
        return pa.table({"fp": fp, "tok": tok, "df": np.concatenate([each[rows], df[frequent]]).astype(np.int64)} | none)

    def told(sent: pa.Table, known: pa.Table) -> pa.Table:
        """One row for each set of a pack: its frequent shingles with their frequencies."""
        n, fps, raw = (sent.column(c)[0].as_py() for c in ("n", "fps", "packed"))
        h, owner = unpack(raw, n)
        tok, df = known.column("tok").to_numpy().view(np.uint64), known.column("df").to_numpy()
        order = np.argsort(tok)
        df = df[order][np.searchsorted(tok[order], h)]
        order = np.argsort(owner, kind="stable")
        names = np.frombuffer(fps, np.int64)
        ends = np.searchsorted(owner[order], np.arange(len(names) + 1)).astype(np.int32)
        each = pa.StructArray.from_arrays([pa.array(df[order]), pa.array(h[order].view(np.int64))], names=["df", "tok"])
        return pa.table({"fp": names, "often": pa.ListArray.from_arrays(pa.array(ends), each)})

    packed = docs.select(text_col).mapInArrow(blocks, "p int, pack long, n long, fps binary, packed binary")
    met = keep(packed.groupBy("p").applyInArrow(meet, "fp long, tok long, df long, pack long, n long, fps binary, packed binary"), "shared")
    known = met.filter("tok IS NOT NULL AND df IS NULL").select("pack", "tok").join(met.filter("fp IS NULL AND df IS NOT NULL").select("tok", "df").hint("merge"), "tok").withColumnRenamed("pack", "of")
    sent = met.filter("packed IS NOT NULL").select("pack", "n", "fps", "packed")
    kind = "array<struct<df:bigint,tok:bigint>>"
    often = sent.groupBy("pack").cogroup(known.groupBy("of")).applyInArrow(told, f"fp long, often {kind}")
    light = met.filter("fp IS NOT NULL").select("fp", F.struct("df", "tok").alias("x"), F.lit(None).cast(kind).alias("often"))
    return light.unionByName(often.select("fp", F.lit(None).cast("struct<df:bigint,tok:bigint>").alias("x"), "often"))


def needed(n: Column, percent: int) -> Column:
    """ceil(percent/100 * n) in integers."""
    return F.floor((n * percent + 99) / 100).cast("long")


def index_nodes(shared: DataFrame, sizes: DataFrame, cfg: JoinConfig) -> DataFrame:
    """fp, n, u (private shingles), toks (shared, rare first), bits (parity bitmap of toks), for sets that can link."""
    r = shared.groupBy("fp").agg(F.collect_set("x").alias("t"), F.flatten(F.collect_list("often")).alias("often"))
    # equal sets of different packs may repeat a frequent shingle
    both = F.sort_array(F.concat("t", "often"))
    once = F.transform(F.filter(F.arrays_zip(both.alias("x"), F.concat(F.array(F.lit(None).cast("bigint")), both["tok"]).alias("last")), lambda y: F.coalesce(y["x"]["tok"] != y["last"], y["x"].isNotNull())), lambda y: y["x"])
    r = r.select("fp", F.when(F.size("often") > 0, once).otherwise(F.sort_array("t")).alias("t"))
    r = r.join(sizes, "fp").filter(F.size("t") * 100 >= F.col("n") * cfg.percent)
    r = r.select("fp", "n", (F.col("n") - F.size("t")).alias("u"), F.col("t.tok").alias("toks"))

    def bitmaps(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for toks in batch.column(3):
                t = np.asarray(toks.values).view(np.uint64)
                out.append((np.packbits(np.bincount((t & np.uint64(64 * BITMAP_WORDS - 1)).astype(np.int64), minlength=64 * BITMAP_WORDS) & 1)).view("<i8").tolist())
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out, pa.list_(pa.int64()))], names=[*batch.schema.names, "bits"])

    return r.mapInArrow(bitmaps, "fp long, n long, u long, toks array<long>, bits array<long>")


def components(edges: DataFrame, keep: Scratch) -> DataFrame:
    """v, c: the smallest node reachable from each node of ``edges`` (a, b)."""
    both = keep(edges.select("a", "b").union(edges.select(F.col("b"), F.col("a"))).distinct(), "edges")
    hubs = hot_keys(both, "b")
    now = keep(both.groupBy(F.col("a").alias("v")).agg(F.min("b").alias("m")).select("v", F.least("v", "m").alias("c")), "labels")
    while True:  # labels only fall, and each is a node, so this ends
        jump = now.select(F.col("v").alias("c"), F.col("c").alias("cc"))
        far = lookup(now, jump, "c", "v")
        near = lookup(both, far.select(F.col("v").alias("b"), "cc"), "b", "a", hot=hubs).groupBy(F.col("a").alias("v")).agg(F.min("cc").alias("m"))
        # the least label next to a node lowers the node and the node that its label names
        low = far.join(near.hint("merge"), "v").select("v", "c", F.least("cc", "m").alias("m"))
        low = low.select(F.explode(F.array(F.struct("v", "c", "m"), F.struct(F.col("c").alias("v"), F.lit(None).cast("long").alias("c"), "m"))).alias("x")).select("x.*")
        new = keep(low.groupBy("v").agg(F.max("c").alias("was"), F.min("m").alias("c")), "labels")
        moved = new.filter("c <> was").limit(1).count()
        keep.drop_previous()
        now = new.select("v", "c")
        if not moved:
            break
    return now


def verified(pairs: DataFrame, nodes: DataFrame, cfg: JoinConfig, keep: Scratch) -> DataFrame:
    """a, b of the pairs that link: exact intersection of the shared shingles (private ones cannot meet)."""
    left = nodes.select(F.col("fp").alias("a"), F.col("n").alias("na"), F.col("toks").alias("ta"))
    right = nodes.select(F.col("fp").alias("b"), F.col("n").alias("nb"), F.col("toks").alias("tb"))
    pairs = keep(pairs, "pairs")
    both = lookup(lookup(pairs, left, "a", "b"), right, "b", "a", hot=hot_keys(pairs, "b"))
    m = F.size(F.array_intersect("ta", "tb"))
    return both.filter(100 * m >= cfg.percent * (F.col("na") + F.col("nb") - m)).select("a", "b")


def can_link(cfg: JoinConfig, na: Column, nb: Column, pa_: Column, pb: Column) -> Column:
    """False if the first meeting shingle's places (0-based, private shingles before) forbid a link."""
    most = F.least(na - pa_, nb - pb)
    return 100 * most >= cfg.percent * (most + pa_ + pb)


def pair_columns(x: Column, y: Column) -> list[Column]:
    return [F.least(x, y).alias("a"), F.greatest(x, y).alias("b")]


def short_list_pairs(mixed: DataFrame, nodes: DataFrame, cfg: JoinConfig) -> DataFrame:
    """a, b: candidates of lists that are one block. ``mixed``: tok, fp, n, u, at, c, main (the list's largest component)."""
    d = mixed.join(nodes.select("fp", "bits").hint("merge"), "fp")
    rest = d.filter("c <> main").select("tok", *(F.col(x).alias(x + "2") for x in ("fp", "n", "u", "at", "c", "bits")))
    apart = F.aggregate(F.zip_with("bits", "bits2", lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda s, x: s + x)
    both = (
        (F.col("c") != F.col("c2"))
        & ((F.col("c") == F.col("main")) | (F.col("fp") < F.col("fp2")))
        & can_link(cfg, F.col("n"), F.col("n2"), F.col("at"), F.col("at2"))
        & ((100 + cfg.percent) * (F.col("u") + F.col("u2") + apart) <= (100 - cfg.percent) * (F.col("n") + F.col("n2")))
    )
    met = d.alias("l").join(rest.alias("r").hint("merge"), (F.col("l.tok") == F.col("r.tok")) & both)
    return met.select(*pair_columns(F.col("fp"), F.col("fp2"))).distinct()


def differences(members: DataFrame, nodes: DataFrame, cfg: JoinConfig) -> DataFrame:
    """How each member differs from its centre: home, fp, c, d (shingles in one of the two only), q, own, toks, tail, width.

    ``toks`` are the differing shingles that another member of the centre differs in too, rare first; ``own`` is the
    number of the others, which come before them; ``tail`` the number of the centre's private shingles, in which all
    members differ, at the end; ``width`` is that of a block in ``q``. ``q`` is (100 + p) d - (100 - p) n: two members link
    exactly if their differences have at least (q1 + q2) / (2 (100 + p)) shingles in common.
    """
    one = nodes.select("fp", "n", "u", "toks")
    both = lookup(members.join(one.hint("merge"), "fp"), one.select(F.col("fp").alias("home"), F.col("u").alias("tail"), F.col("toks").alias("base"), F.col("n").alias("size")), "home", "fp", hot=hot_keys(members, "home"))
    both = both.select("home", "fp", "c", "n", "u", "tail", "size", F.concat(F.array_except("toks", "base"), F.array_except("base", "toks")).alias("apart"))
    both = both.withColumn("d", F.col("u") + F.col("tail") + F.size("apart")).drop("u")
    each = both.select("home", "fp", F.explode("apart").alias("tok"))
    often = each.groupBy("home", "tok").agg(F.count("*").alias("f")).filter("f > 1")
    ranked = each.join(often.hint("merge"), ["home", "tok"]).groupBy("home", "fp").agg(F.sort_array(F.collect_list(F.struct("f", "tok"))).alias("t"))
    out = both.drop("apart").join(ranked.select("home", "fp", F.col("t.tok").alias("toks")).hint("merge"), ["home", "fp"], "left")
    out = out.withColumn("toks", F.coalesce("toks", F.array().cast("array<long>")))
    width = (100 + cfg.percent) * F.greatest(F.lit(1), F.floor(F.col("size") / cfg.blocks))
    q = (100 + cfg.percent) * F.col("d") - (100 - cfg.percent) * F.col("n")
    return out.select("home", "fp", "c", "d", q.alias("q"), (F.col("d") - F.col("tail") - F.size("toks")).alias("own"), "toks", "tail", width.alias("width"))


def offered(d: DataFrame, kinds: DataFrame, partners: str, cfg: JoinConfig) -> DataFrame:
    """The shingles that each member offers to each block of partners: home, fp, c, main, q, kind (its own block), other
    (the partners' block), tok (null: the centre's private ones), left (differing shingles from this one on)."""
    x = lookup(d, kinds.select("home", F.col(partners).alias("others")), "home", "fp").withColumn("other", F.explode("others"))
    common = F.greatest(F.lit(1), F.ceil((F.col("q") + F.col("other") * F.col("width")) / (2 * (100 + cfg.percent))))
    x = x.withColumn("reach", (F.col("d") - common + 1 - F.col("own")).cast("int")).filter("reach > 0")
    whole = F.when((F.col("reach") > F.size("toks")) & (F.col("tail") > 0), F.concat(F.col("toks"), F.array(F.lit(None).cast("long")))).otherwise(F.col("toks"))
    x = x.select("home", "fp", "c", "main", "q", "d", "own", "kind", "other", F.posexplode(F.slice(whole, 1, F.col("reach"))).alias("i", "tok"))
    return x.withColumn("left", F.col("d") - F.col("own") - F.col("i")).drop("i", "own", "d")


def offers(members: DataFrame, nodes: DataFrame, cfg: JoinConfig, keep: Scratch) -> tuple[DataFrame, DataFrame]:
    """What left-over members offer, and what all members offer to them."""
    main = members.groupBy("home", "c").agg(F.count("*").alias("k")).groupBy("home").agg(F.max(F.struct("k", "c")).alias("x"))
    d = lookup(differences(members, nodes, cfg), main.select("home", F.col("x.c").alias("main")), "home", "fp", hot=hot_keys(members, "home"))
    d = keep(d.withColumn("kind", F.floor(F.col("q") / F.col("width")).cast("long")), "differences")
    kinds = d.select("home", "kind", (F.col("c") != F.col("main")).alias("rest")).distinct()
    kinds = kinds.groupBy("home").agg(F.collect_set("kind").alias("all"), F.collect_set(F.when(F.col("rest"), F.col("kind"))).alias("rest"))
    return offered(d.filter("c <> main"), kinds, "all", cfg), offered(d, kinds, "rest", cfg)


def centre_pairs(members: DataFrame, nodes: DataFrame, cfg: JoinConfig, keep: Scratch) -> DataFrame:
    """a, b: candidates among the members of long lists, each answered by how it differs from its list's centre.

    ``members``: home (the centre), fp, c (component); pairs of one component are of no interest. Members are cut into
    blocks by their ``q``. For every block of partners a member offers only as many of its differing shingles, rarest
    first, as such partners may make it share: blocks in which that is none are skipped as a whole, and what is offered
    is mostly a member's own and meets nobody. So members that resemble the centre but link to nothing cost no pairs.
    """
    mine, theirs = (x.alias(k) for x, k in zip(offers(members, nodes, cfg, keep), "lr", strict=True))
    on = (F.col("l.home") == F.col("r.home")) & F.col("l.tok").eqNullSafe(F.col("r.tok")) & (F.col("l.kind") == F.col("r.other")) & (F.col("l.other") == F.col("r.kind"))
    may = (
        (F.col("l.c") != F.col("r.c"))
        & ((F.col("r.c") == F.col("r.main")) | (F.col("l.fp") < F.col("r.fp")))
        & (2 * (100 + cfg.percent) * F.least("l.left", "r.left") >= F.col("l.q") + F.col("r.q"))
    )
    return mine.join(theirs.hint("merge"), on & may).select(*pair_columns(F.col("l.fp"), F.col("r.fp"))).distinct()


def links(docs: DataFrame, sizes: DataFrame, cfg: JoinConfig, text_col: str, keep: Scratch) -> DataFrame:
    """a, b: enough links between different sets to connect every component of the full link graph."""
    nodes = keep(index_nodes(shared_shingles(docs, cfg, text_col, keep), sizes, cfg), "nodes")
    first = F.col("n") - needed(F.col("n"), cfg.percent) + 1 - F.col("u")
    lists = nodes.filter(first > 0).select("fp", "n", "u", F.posexplode(F.slice("toks", 1, first.cast("int"))).alias("i", "tok"))
    lists = keep(lists.select("tok", "fp", "n", "u", (F.col("u") + F.col("i")).alias("at")), "lists")
    found = nodes.limit(0).select(F.col("fp").alias("a"), F.col("fp").alias("b"))
    labelled = lists.withColumn("c", F.col("fp"))
    for k in range(cfg.rounds):
        # the centre of a list: first the set with the fewest private shingles, then any
        rank = F.struct("u", "n", "fp", "at", "c") if k == 0 else F.struct(F.xxhash64("fp", F.lit(k)).alias("h"), "fp", "n", "at", "c")
        centre = labelled.groupBy("tok").agg(F.min(rank).alias("x"), F.min("c").alias("lo"), F.max("c").alias("hi")).filter("lo < hi")
        centre = centre.select("tok", *(F.col(f"x.{c}").alias(c + "2") for c in ("fp", "n", "at", "c")))
        p = lookup(labelled, centre, "tok", "fp").filter((F.col("c") != F.col("c2")) & can_link(cfg, F.col("n"), F.col("n2"), F.col("at"), F.col("at2")))
        new = verified(p.select(*pair_columns(F.col("fp"), F.col("fp2"))).distinct(), nodes, cfg, keep)
        labels = components(found.unionByName(new), keep)
        found = labels.filter("v <> c").select(F.col("c").alias("a"), F.col("v").alias("b"))  # the same components
        labelled = keep(lists.join(labels.withColumnRenamed("v", "fp").hint("merge"), "fp", "left").withColumn("c", F.coalesce("c", "fp")), "lists")
    # what is left: lists that still hold several components
    share = labelled.groupBy("tok", "c").agg(F.count("*").alias("k"), F.min(F.struct("u", "n", "fp")).alias("x"))
    share = share.groupBy("tok").agg(F.max(F.struct("k", "c")).alias("most"), F.count("*").alias("cs"), F.sum("k").alias("m"), F.min("x").alias("x")).filter("cs > 1")
    mixed = keep(lookup(labelled, share.select("tok", F.col("most.c").alias("main"), "m", F.col("x.fp").alias("home")), "tok", "fp"), "mixed")
    short = short_list_pairs(mixed.filter(F.col("m") <= cfg.short), nodes, cfg)
    members = mixed.filter((F.col("m") > cfg.short) & (F.col("fp") != F.col("home"))).select("home", "fp", "c").distinct()
    members = keep(members, "members")
    last = short.union(centre_pairs(members, nodes, cfg, keep)).distinct()
    return found.unionByName(verified(last, nodes, cfg, keep))


def labelled_sets(docs: DataFrame, cfg: JoinConfig, id_col: str, text_col: str) -> DataFrame:
    """doc_id, n, fp, text_hash, c (least fp of the component; null without shingles) for each row of ``docs``."""
    with Scratch(docs.sparkSession) as keep:
        d = keep(document_sets(docs, cfg, id_col, text_col), "sets")
        sizes = d.filter("n > 0").groupBy("fp").agg(F.max("n").alias("n"))
        labels = components(links(docs, sizes, cfg, text_col, keep), keep)
        return stored(lookup(d, labels.withColumnRenamed("v", "fp"), "fp", "doc_id", "left").withColumn("c", F.coalesce("c", "fp")), "labelled")


def join_components(docs: DataFrame, cfg: JoinConfig = JoinConfig(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_shingles, component_id, fp for each row of ``docs``."""
    d = labelled_sets(docs, cfg, id_col, text_col)
    least = d.filter("n > 0").groupBy("c").agg(F.min("doc_id").alias("component_id"))
    out = lookup(d.filter("n > 0"), least, "c", "doc_id").select("doc_id", F.col("n").alias("n_shingles"), "component_id", "fp")
    alone = d.filter("n = 0").select("doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("component_id"), "fp")
    return out.unionByName(alone)


def keep_one(docs: DataFrame, cfg: JoinConfig = JoinConfig(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of each component, with all columns of ``docs``: of its smallest id (null is largest), then of the least
    fingerprint and text hash. Rows are told apart by id and 64-bit hash of the text, so ids may be null or repeat;
    rows without shingles stay, and only rows of equal id and text become one."""
    row = lambda i, h: [i.isNull().alias("__none"), F.coalesce(i.cast("long"), F.lit(0)).alias("__id"), h.alias("__text")]
    d = labelled_sets(docs, cfg, id_col, text_col)
    best = d.filter("n > 0").groupBy("c").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "fp", "text_hash")).alias("x")).select("x.*")
    keep = best.select("doc_id", "text_hash").union(d.filter("n = 0").select("doc_id", "text_hash").distinct())
    keep = keep.select(*row(F.col("doc_id"), F.col("text_hash")))
    stay = docs.select("*", *row(F.col(id_col), F.xxhash64(text_col))).join(keep.hint("merge"), keep.columns, "left_semi")
    return stay.dropDuplicates(keep.columns).select(*docs.columns)
