"""Mixing sources to target weights, on built-in functions only.

Target: sources in code-point order, null last, take the weights in turn and share all words by weight; a target
stops at ``cap`` times its source's size and the excess is shared again by weight. That fixpoint has a closed
form: sources stop in order of size over weight, so one ordered pass finds where stopping ends.

Packing: a source's documents, in hash order, form one stream of words that is cut into blocks of ``block`` words;
prefix sums run over hash buckets first and inside buckets then, so no task holds a source.

Drawing: the mix has N slots, each worth one block, in output shards of ``shard_slots`` slots; a source's target is
K(s) of them. Each shard draws its source counts from the multinomial law with the weights K(s) / N: every slot's hash
picks a source, and slots are counted by (shard, source). Draws of all shards together miss K(s) by chance, so they
are settled: a source's draws beyond K(s) are left out, where shards come last, and what a source lacks then fills
shards after the drawn ones. So targets and the cap hold exactly, and the settled part shrinks as 1 / sqrt(N).

A source's slots are numbered through the shards. The k-th is mapped through the source's own permutation (a new one
for each pass over its n blocks) to a block index, and blocks are joined by (source, index); inside a shard another
permutation mixes the sources. Permutations are swap-or-not shuffles over 64-bit hashes: exact on any range, computed
row by row, equal on every run.

Edge cases: null texts have size 0 and are taken 0 times; empty sources have target 0; repeated rows are packed
one by one; ties do not matter as equal rows are interchangeable; an empty table gives no rows; other columns of
the input, whatever their names, are not read (``mixed_documents`` keeps them).
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .texts import WORD, stored


#: Facts of so many sources may be broadcast: some MB.
FEW_SOURCES = 50_000


@dataclass(frozen=True)
class MixConfig:
    weights: tuple[float, ...] = (5.0, 2.0, 1.0)
    cap: int = 3
    block: int = 64
    shard_slots: int = 1024
    #: Hash buckets of a source for the two-level prefix sums.
    buckets: int = 1 << 14
    #: Cells of the range of slots in which a drawn slot looks up its source.
    cells: int = 4096
    rounds: int = 20
    seed: int = 11


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def targets(sizes: DataFrame, cfg: MixConfig = MixConfig()) -> DataFrame:
    """source, source_size, target from one row (source, source_size) for each source; all windows are over sources."""
    w = F.element_at(F.array(*map(F.lit, cfg.weights)), (F.pmod(F.col("place") - 1, F.lit(len(cfg.weights))) + 1).cast("int"))
    s = sizes.withColumn("place", F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last()))).withColumn("w", w.cast("double"))
    everything = Window.partitionBy()
    stop_order = Window.orderBy(F.col("source_size") / F.col("w"), "place")
    upto, after = stop_order.rowsBetween(Window.unboundedPreceding, -1), stop_order.rowsBetween(0, Window.unboundedFollowing)
    # level if exactly the sources before this one in stopping order have stopped
    level = (F.sum("source_size").over(everything) - cfg.cap * F.coalesce(F.sum("source_size").over(upto), F.lit(0))) / F.sum("w").over(after)
    s = s.withColumn("level", level).withColumn("free", F.col("level") * F.col("w") <= cfg.cap * F.col("source_size"))
    s = s.withColumn("final", F.min(F.when(F.col("free"), F.struct((F.col("source_size") / F.col("w")).alias("r"), F.col("place").alias("p"), F.col("level").alias("level")))).over(everything))
    target = F.when(F.col("source_size") == 0, 0.0).when(F.col("final").isNull(), cfg.cap * F.col("source_size")).otherwise(F.least(F.col("final.level") * F.col("w"), (cfg.cap * F.col("source_size")).cast("double")))
    return s.select("source", "source_size", target.cast("double").alias("target"))


def shuffled(x: Column, n: Column, key: list[Column], cfg: MixConfig) -> Column:
    """Where a pseudorandom permutation of 0..n-1, chosen by ``key``, puts ``x`` (swap-or-not)."""

    def turn(x: Column, r: Column) -> Column:
        shift = F.pmod(F.xxhash64(F.lit(cfg.seed), r, *key), n)
        partner = F.pmod(shift + n - x, n)
        swap = F.pmod(F.xxhash64(F.lit(cfg.seed + 1), r, F.greatest(x, partner), *key), F.lit(2)) == 1
        return F.when(swap, partner).otherwise(x)

    return F.aggregate(F.sequence(F.lit(1), F.lit(cfg.rounds)), x.cast("long"), turn)


def row_hash(cfg: MixConfig, *names: str) -> Column:
    return F.xxhash64(F.lit(cfg.seed), *names)


def packed(docs: DataFrame, cfg: MixConfig = MixConfig(), id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", keep_text: bool = False) -> DataFrame:
    """doc_id, source, size, h, s, bucket (and the text, if kept) of each document."""
    size = word_count(F.col(text_col))
    h = row_hash(cfg, id_col, text_col, source_col)
    d = docs.select(F.col(id_col).alias("doc_id"), F.col(source_col).alias("source"), size.alias("size"), h.alias("h"), *([F.col(text_col).alias("text")] if keep_text else []))
    # null and "" must stay different sources in joins: a flag goes with the name
    d = d.withColumn("s", F.coalesce(F.concat(F.lit("="), "source"), F.lit("")))
    return d.withColumn("bucket", F.pmod(F.shiftrightunsigned("h", 20), F.lit(cfg.buckets)))


def plan(d: DataFrame, cfg: MixConfig = MixConfig()) -> tuple[DataFrame, DataFrame]:
    """(documents with begin, where they begin in their source's stream of words; source facts): facts have s,
    source_size, target, blocks n, slots k, first (slots of the sources before), deck (slots of all)."""
    sums = stored(d.groupBy("s", "source", "bucket").agg(F.sum("size").alias("words")), "mix-sums")
    facts = targets(sums.groupBy("source").agg(F.sum("words").alias("source_size")), cfg)
    n = F.ceil(F.col("source_size") / cfg.block).cast("long")
    facts = facts.select(F.coalesce(F.concat(F.lit("="), "source"), F.lit("")).alias("s"), "source_size", "target", n.alias("n"))
    # the last block of a source is part empty: a slot is worth source_size / n words on average
    k = F.when(F.col("n") > 0, F.least(F.round(F.col("target") * F.col("n") / F.col("source_size")).cast("long"), cfg.cap * F.col("n"))).otherwise(F.lit(0)).cast("long")
    order = Window.orderBy("s").rowsBetween(Window.unboundedPreceding, -1)
    facts = facts.withColumn("k", k).withColumn("first", F.coalesce(F.sum("k").over(order), F.lit(0))).withColumn("deck", F.sum("k").over(Window.partitionBy()))
    facts = stored(facts, "mix-facts")
    before = sums.select("s", "bucket", F.coalesce(F.sum("words").over(Window.partitionBy("s").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    inside = Window.partitionBy("s", "bucket").orderBy("h", "doc_id").rowsBetween(Window.unboundedPreceding, -1)
    d = d.withColumn("inside", F.coalesce(F.sum("size").over(inside), F.lit(0)))
    return d.join(before, ["s", "bucket"]).withColumn("begin", F.col("before") + F.col("inside")).drop("before", "inside"), facts


def counted_out(d: DataFrame, last: Column, name: str, run: int = 4096) -> DataFrame:
    """Each row of ``d`` with ``name`` = 0 .. ``last``: by runs of runs, so that no array grows, on all partitions."""
    far = 1 << 24
    d = d.filter(last >= 0).withColumn("__last", last).withColumn("__far", F.explode(F.sequence(F.lit(0).cast("long"), "__last", F.lit(far).cast("long"))))
    d = d.withColumn("__from", F.explode(F.sequence("__far", F.least(F.col("__far") + far - 1, F.col("__last")), F.lit(run).cast("long"))))
    # a number of partitions given by hand, which adaptive execution leaves alone: the rows are few before they are exploded
    d = d.repartition(int(d.sparkSession.conf.get("spark.sql.shuffle.partitions")), "__from", *[c for c in d.columns if c in ("s", "shard")])
    return d.withColumn(name, F.explode(F.sequence("__from", F.least(F.col("__from") + run - 1, F.col("__last"))))).drop("__last", "__far", "__from")


def by_source(facts: DataFrame, part: DataFrame) -> DataFrame:
    """``part``, some rows for each source, as the side of a join with rows that are exploded from few, whose size
    Spark underestimates: broadcast if the sources are few, else never."""
    return F.broadcast(part) if facts.limit(FEW_SOURCES + 1).count() <= FEW_SOURCES else part.hint("merge")


def drawn_counts(facts: DataFrame, cfg: MixConfig = MixConfig()) -> DataFrame:
    """shard, s, drawn: multinomial source counts of each shard, one independent draw for each of its slots."""
    of = facts.filter("k > 0").select("s", "first", "k", "deck")
    cell = lambda x, deck: F.floor(x * F.lit(float(cfg.cells)) / deck).cast("int")
    ends = of.withColumn("cell", F.explode(F.sequence(cell(F.col("first"), F.col("deck")), cell(F.col("first") + F.col("k") - 1, F.col("deck"))))).drop("deck")
    slot = counted_out(of.groupBy().agg(F.max("deck").alias("deck")).filter("deck > 0"), F.col("deck") - 1, "slot")
    slot = slot.withColumn("x", F.pmod(F.xxhash64(F.lit(cfg.seed + 2), "slot"), F.col("deck")))
    slot = slot.select(F.floor(F.col("slot") / cfg.shard_slots).cast("long").alias("shard"), "x", cell(F.col("x"), F.col("deck")).alias("cell"))
    met = slot.join(by_source(facts, ends), (slot.cell == ends.cell) & (F.col("x") >= F.col("first")) & (F.col("x") < F.col("first") + F.col("k")))
    return met.groupBy("shard", "s").agg(F.count("*").alias("drawn"))


def shard_counts(facts: DataFrame, cfg: MixConfig = MixConfig()) -> DataFrame:
    """shard, s, before, count: how many slots of a source a shard has, and how many the shards before it have."""
    drawn = stored(drawn_counts(facts, cfg), "mix-draws").withColumn("far", F.floor(F.col("shard") / 4096).cast("long"))
    sums = drawn.groupBy("s", "far").agg(F.sum("drawn").alias("all"))
    offset = sums.select("s", "far", (F.sum("all").over(Window.partitionBy("s").orderBy("far")) - F.col("all")).alias("offset"))
    near = F.sum("drawn").over(Window.partitionBy("s", "far").orderBy("shard")) - F.col("drawn")
    d = drawn.withColumn("near", near).join(offset.hint("merge"), ["s", "far"]).join(by_source(facts, facts.select("s", "k")), "s")
    d = d.withColumn("before", F.col("offset") + F.col("near"))
    d = d.select("shard", "s", "before", F.least(F.col("drawn"), F.col("k") - F.col("before")).alias("count")).filter("count > 0")
    # what a source's draws leave open, in shards after the drawn ones
    had = sums.groupBy("s").agg(F.sum("all").alias("had"))
    lack = facts.filter("k > 0").join(had.hint("merge"), "s", "left").select("s", "deck", F.least(F.coalesce("had", F.lit(0)), F.col("k")).alias("had"), "k").withColumn("open", F.col("k") - F.col("had")).filter("open > 0")
    lack = lack.withColumn("at", F.sum("open").over(Window.orderBy("s")) - F.col("open"))
    shard = F.explode(F.sequence(F.floor(F.col("at") / cfg.shard_slots), F.floor((F.col("at") + F.col("open") - 1) / cfg.shard_slots)))
    lack = lack.withColumn("i", shard)
    lo = F.greatest(F.col("i") * cfg.shard_slots, F.col("at"))
    hi = F.least((F.col("i") + 1) * cfg.shard_slots, F.col("at") + F.col("open"))
    late = lack.select((F.ceil(F.col("deck") / cfg.shard_slots) + F.col("i")).cast("long").alias("shard"), "s", (F.col("had") + lo - F.col("at")).alias("before"), (hi - lo).alias("count"))
    return d.unionByName(late)


def slots(facts: DataFrame, cfg: MixConfig = MixConfig()) -> DataFrame:
    """The mix itself: shard, place in the shard, source s, block index, pass. One row for each slot."""
    shard = Window.partitionBy("shard")
    c = shard_counts(facts, cfg).withColumn("in_shard", F.sum("count").over(shard)).withColumn("offset", F.sum("count").over(shard.orderBy("s")) - F.col("count"))
    k = counted_out(c.join(by_source(facts, facts.select("s", "n")), "s"), F.col("count") - 1, "i")
    number = F.col("before") + F.col("i")
    k = k.withColumn("pass", F.floor(number / F.col("n")).cast("long"))
    place = shuffled(F.col("offset") + F.col("i"), F.col("in_shard"), [F.lit(-1), F.col("shard")], cfg)
    block = shuffled(F.pmod(number, F.col("n")), F.col("n"), [F.col("s"), F.col("pass")], cfg)
    return k.select("shard", place.alias("place"), "s", block.alias("block"), "pass")


def pieces(d: DataFrame, cfg: MixConfig = MixConfig()) -> DataFrame:
    """The parts of documents that lie in one block: s, block, lo, hi (words of the document, hi excluded)."""
    last = F.floor((F.col("begin") + F.col("size") - 1) / cfg.block).cast("long")
    p = d.filter("size > 0").withColumn("block", F.explode(F.sequence(F.floor(F.col("begin") / cfg.block).cast("long"), last)))
    lo = F.greatest(F.col("block") * cfg.block - F.col("begin"), F.lit(0))
    hi = F.least((F.col("block") + 1) * cfg.block - F.col("begin"), F.col("size"))
    return p.withColumn("lo", lo).withColumn("hi", hi)


def mix_words(docs: DataFrame, cfg: MixConfig = MixConfig(), **cols) -> DataFrame:
    """doc_id, size, source_size, target, taken for each row of ``docs``."""
    d, facts = plan(packed(docs, cfg, **cols), cfg)
    d = stored(d.withColumn("row", F.monotonically_increasing_id()), "mix-docs")
    times = slots(facts, cfg).groupBy("s", "block").agg(F.count("*").alias("times"))
    # slots are exploded from few rows, so their size is underestimated: the joins must not be broadcast on that ground
    taken = pieces(d, cfg).join(times.hint("merge"), ["s", "block"]).groupBy("row").agg(F.sum((F.col("hi") - F.col("lo")) * F.col("times")).alias("taken"))
    return d.join(taken.hint("merge"), "row", "left").join(facts.select("s", "source_size", "target"), "s").select("doc_id", "size", "source_size", "target", F.coalesce("taken", F.lit(0)).cast("long").alias("taken"))


def shard_blocks(docs: DataFrame, cfg: MixConfig = MixConfig(), id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """The mix as output shards: shard, place, source, words (of the block in that place, ``block`` at most)."""
    inner = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"), F.col(source_col).alias("source"))
    d, facts = plan(packed(inner, cfg, keep_text=True), cfg)
    facts = stored(facts.join(d.select("s", "source").distinct(), "s"), "mix-facts")
    p = pieces(d, cfg).withColumn("words", F.regexp_extract_all("text", F.lit(rf"({WORD})"), 1))
    p = p.select("s", "block", "begin", "doc_id", F.slice("words", (F.col("lo") + 1).cast("int"), (F.col("hi") - F.col("lo")).cast("int")).alias("words"))
    full = p.groupBy("s", "block").agg(F.flatten(F.transform(F.sort_array(F.collect_list(F.struct("begin", "doc_id", "words"))), lambda x: x["words"])).alias("words"))
    return slots(facts, cfg).join(full.hint("merge"), ["s", "block"]).join(by_source(facts, facts.select("s", "source")), "s").select("shard", "place", "source", "words")


def mixed_documents(docs: DataFrame, cfg: MixConfig = MixConfig(), id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """The mix as documents, with the columns of ``docs``: one row for each document and pass that takes any of it.

    A pass that takes all blocks of a document gives the row unchanged; otherwise its text holds the taken words
    in their order, with the white space that follows each. Equal rows are told apart by a number, so each is mixed.
    """
    h = row_hash(cfg, id_col, text_col, source_col)
    d, facts = plan(packed(docs, cfg, id_col, text_col, source_col), cfg)
    d = d.withColumn("twin", F.row_number().over(Window.partitionBy("h", "doc_id").orderBy("begin")))
    got = pieces(d, cfg).join(slots(facts, cfg).hint("merge"), ["s", "block"]).groupBy("h", "doc_id", "twin", "size", "pass").agg(F.sort_array(F.collect_list(F.struct("lo", "hi"))).alias("parts"), F.sum(F.col("hi") - F.col("lo")).alias("words"))
    got = got.select(F.col("h").alias("got_h"), F.col("doc_id").alias("got_id"), F.col("twin").alias("got_twin"), F.when(F.col("words") < F.col("size"), F.col("parts")).alias("parts"))
    # the input's columns travel in one struct, so that none of their names meets one of these
    full = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row"), h.alias("h"), F.col(id_col).alias("id"))
    full = full.withColumn("twin", F.row_number().over(Window.partitionBy("h", "id").orderBy(F.lit(0))))
    full = full.join(got.hint("merge"), (F.col("h") == F.col("got_h")) & F.col("id").eqNullSafe(F.col("got_id")) & (F.col("twin") == F.col("got_twin")))
    text = F.col(f"row.`{text_col}`")
    # explode of one array is a barrier: inside the lambda below the words would be taken from the text for every part
    words = F.regexp_extract_all(text, F.lit(rf"({WORD}[\x20\x09-\x0D]*)"), 1)
    full = full.withColumn("all_words", F.explode(F.array(F.when(F.col("parts").isNotNull(), words))))
    cut = F.array_join(F.flatten(F.transform("parts", lambda p: F.slice("all_words", (p["lo"] + 1).cast("int"), (p["hi"] - p["lo"]).cast("int")))), "")
    full = full.withColumn("new_text", F.when(F.col("parts").isNull(), text).otherwise(cut))
    # one evaluation of the cut: two copies of the lambda in one projection would share its variable
    put = {text_col: F.col("new_text"), "n_chars": F.char_length("new_text").cast("long")}
    return full.select(*(put.get(c, F.col(f"row.`{c}`")).alias(c) for c in docs.columns))
