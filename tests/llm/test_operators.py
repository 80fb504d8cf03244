"""Each operator against brute force, a library, a round trip or held-out rows."""

from __future__ import annotations

import collections
import hashlib
import random
import re
import zlib
from dataclasses import replace

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from pdpview.llm import bpe_count, decontaminate, langid, mixing, quality, rans, registry, sentence_spans, setjoin, token_files, toxicity, url_rules
from pdpview.llm.texts import Scratch

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size long, n int, h string, taken long, component_id string"


def docs_of(spark, rows):
    """Documents with columns whose names clash with the operators' own."""
    return spark.createDataFrame([(i, t, lang, src, len(t or ""), -1, 0, "x", -5, "c") for i, t, lang, src in rows], SCHEMA)


def odd_rows():
    long = " ".join(f"w{k % 977}" for k in range(30_000))
    return [
        (1, None, None, None),
        (2, "", "en", ""),
        (3, " \n\t ", None, "s"),
        (4, "one", "en", None),
        (5, "The cat sat on the mat. The cat sat on the mat!\nIt was <|endoftext|> there.", "en", "s"),
        (5, "The cat sat on the mat. The cat sat on the mat!\nIt was <|endoftext|> there.", "en", "s"),
        (6, long, "en", "t"),
        (7, long + " end", None, None),
        (None, "no id here at all , is there", "en", "t"),
        (None, None, "fr", "t"),
        (8, "\x00\x01 日本語 ½ été 👍🏽  double  spaces \r\n", "fr", "\u00e9"),
    ]


@pytest.fixture(scope="module")
def odd(spark):
    return docs_of(spark, odd_rows()).repartition(3).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return docs_of(spark, []).cache()


@pytest.fixture(scope="module")
def docs(spark, small):
    return registry.table(spark, small, "documents").cache()


@pytest.fixture(scope="module")
def rows(docs):
    return sorted(docs.collect(), key=lambda r: r.doc_id)


# --- quality -------------------------------------------------------------------------------------------------------


def base_brute(text):
    t = text or ""
    w = WORD.findall(t)
    lines = [x for x in t.split("\n") if WORD.search(x)]
    tri = collections.Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
    hit = {j for i in range(len(w) - 2) if tri[tuple(w[i : i + 3])] > 1 for j in (i, i + 1, i + 2)}
    n = len(w)
    return n, sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(hit), n < 50 or 100 * len(hit) > 50 * n


def test_quality_base(rows):
    texts = [r.text for r in rows] + [t for _, t, _, _ in odd_rows()]
    for t, got in zip(texts, quality.judge(texts, {}, quality.QualityRules()), strict=True):
        assert got[:6] == base_brute(t)


def test_quality_verdict(spark, small, rows):
    out = {r.doc_id: r for r in registry.op1_quality(spark, small).collect()}
    assert len(out) == len(rows) and not any(r.kept and r.base_failed for r in out.values())
    good = {r.doc_id for r in registry.table(spark, small, "labels").filter("quality = 1").collect()}
    judged = [out[i] for i in good if not out[i].base_failed]
    assert judged and all(r.kept for r in judged)


def test_js_distance():
    d = quality.js_distance(np.array([[1.0, 0], [0, 1.0], [1, 1]]), np.array([4.0, 0]))
    assert d[0] == 0 and d[1] == 1 and 0 < d[2] < 1


def test_quality_edges(odd, empty):
    assert quality.assess(odd).count() == len(odd_rows()) and quality.assess(empty).count() == 0
    kept = quality.keep_good(odd, quality.QualityRules(min_words=1, max_repeat_percent=1000, max_class_distance=2, max_word_distance=2))
    assert kept.columns == odd.columns and kept.count() == len(odd_rows()) - 4


def test_quality_of_other_languages(spark, docs):
    """Clean texts of a language without a fixed list stay, noise among them goes; unknown languages are not judged."""
    rng = random.Random(6)
    syllable = lambda: "".join(rng.choice(x) for x in ("bcdfglmnprstvz", "aeiou"))
    word = lambda: "".join(syllable() for _ in range(rng.randint(2, 4)))
    small_words = "di che il la un per non una sono con del si da come ma le anche se i al piu della ha questo nel".split()
    clean = lambda: " ".join(rng.choice(small_words) if rng.random() < 0.45 else word() for _ in range(260))
    noise = [" ".join(word() for _ in range(260)), " ".join("#%&*" * 2 + str(rng.random()) for _ in range(260))]
    made = [(1_000_000 + k, clean(), "it", "s") for k in range(30)] + [(1_000_100 + k, t, "it", "s") for k, t in enumerate(noise)]
    made += [(1_000_200 + k, clean(), lang, "s") for k, lang in enumerate([None, "", None])]
    both = docs.select("doc_id", "text", "lang").union(docs_of(spark, made).select("doc_id", "text", "lang"))
    out = {r.doc_id: r for r in quality.assess(both).collect()}
    kept = {r.doc_id for r in quality.keep_good(both).collect()}
    assert kept == {i for i, r in out.items() if r.kept}
    assert all(out[i].kept == (not 1_000_100 <= i < 1_000_200) for i, _, _, _ in made)
    assert all(out[1_000_200 + k].class_js is None and out[1_000_200 + k].word_js is None for k in range(3))
    given = {r.doc_id: r for r in quality.assess(docs).collect()}
    assert all(out[i] == r for i, r in given.items())


# --- join ----------------------------------------------------------------------------------------------------------

LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def components_brute(rows):
    sets = []
    for _, t in rows:
        w = WORD.findall((t or "").translate(LOWER))
        sets.append({tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set())
    up = list(range(len(rows)))

    def find(a):
        while up[a] != a:
            a = up[a]
        return a

    for a in range(len(rows)):
        for b in range(a):
            m = len(sets[a] & sets[b])
            if m and 100 * m >= 80 * (len(sets[a]) + len(sets[b]) - m):
                up[find(a)] = find(b)
    least = {}
    for k, (i, _) in enumerate(rows):
        if sets[k] and i is not None:
            c = find(k)
            least[c] = min(least.get(c, i), i)
    return sorted((repr(i), len(sets[k]), repr(least.get(find(k)) if sets[k] else i)) for k, (i, _) in enumerate(rows))


def joined(df):
    return sorted((repr(r.doc_id), r.n_shingles, repr(r.component_id)) for r in setjoin.join_components(df).collect())


def test_join_on_documents(docs, rows):
    assert joined(docs) == components_brute([(r.doc_id, r.text) for r in rows])


def test_join_on_near_copies(spark):
    """A chain-like group of near copies, exact copies, a shared passage, and texts below five words."""
    rng = random.Random(3)
    word = lambda: "".join(rng.choices("abcdefgh", k=5))
    base, passage = [word() for _ in range(120)], [word() for _ in range(40)]
    rows, i = [], 0
    for _ in range(120):
        w = list(base)
        for _ in range(rng.randint(0, 6)):
            w[rng.randrange(len(w))] = word()
        rows.append((i := i + 1, " ".join(w)))
    for _ in range(40):
        w = [word() for _ in range(60)]
        rows.append((i := i + 1, " ".join(w[:30] + passage + w[30:])))
    rows += [(i + 1 + k, "A b C" if k % 2 else "a B c d") for k in range(6)]
    df = docs_of(spark, [(a, t, "en", "s") for a, t in rows]).repartition(5)
    assert joined(df) == components_brute(rows)


def test_join_edges(odd, empty):
    assert joined(odd) == components_brute([(i, t) for i, t, _, _ in odd_rows()]) and joined(empty) == []
    kept = setjoin.keep_one(odd)
    assert kept.columns == odd.columns
    assert sorted(r.doc_id for r in kept.collect() if r.doc_id is not None) == [1, 2, 3, 4, 5, 6, 8]


def test_keep_one_with_odd_ids(spark):
    """Null and repeated ids: each component keeps one row, and only equal rows of other texts become one."""
    a, b, c, d, e = (" ".join(f"{x}{k}" for k in range(60)) for x in "abcde")
    rows = [(1, a), (1, b), (None, c), (None, d), (None, a + " more"), (2, b), (2, e), (2, e), (None, d), (3, ""), (3, ""), (3, None), (None, None), (None, None), (None, " ")]
    kept = setjoin.keep_one(docs_of(spark, [(i, t, "en", "s") for i, t in rows]).repartition(3))
    key = lambda x: tuple((v is not None, v) for v in x)
    assert sorted(((r.doc_id, r.text) for r in kept.collect()), key=key) == sorted([(1, a), (1, b), (None, c), (None, d), (2, e), (3, ""), (3, None), (None, None), (None, " ")], key=key)


def group_rows(spark, size):
    """What the join's last stage makes of one group of near copies: offered shingles, their meetings, candidates."""
    rng = random.Random(12)
    word = lambda: "".join(rng.choices("abcdefghijklmnop", k=7))
    base, rows = [word() for _ in range(150)], []
    for i in range(size):
        w = list(base)
        for _ in range(rng.randint(0, 6)):
            w[rng.randrange(len(w))] = word()
        rows.append((i, " ".join(w), "en", "s"))
    docs, seen = docs_of(spark, rows), {}
    real = setjoin.offers

    def spy(members, nodes, cfg, keep):
        mine, theirs = real(members, nodes, cfg, keep)
        key = lambda d, a, b: d.groupBy("home", F.coalesce("tok", F.lit(0)).alias("tok"), F.col(a).alias("x"), F.col(b).alias("y")).agg(F.count("*").alias("k"))
        met = key(mine, "kind", "other").join(key(theirs, "other", "kind").withColumnRenamed("k", "k2"), ["home", "tok", "x", "y"])
        seen.update(members=members.count(), mine=mine.count(), theirs=theirs.count(), met=met.agg(F.sum(F.col("k") * F.col("k2"))).first()[0] or 0)
        return mine, theirs

    setjoin.offers = spy
    try:
        again = sorted((r.doc_id, r.component_id) for r in setjoin.join_components(docs).collect())
    finally:
        setjoin.offers = real
    assert again == sorted((int(a), int(c)) for a, _, c in components_brute([(i, t) for i, t, _, _ in rows]))
    return seen


def test_join_rows_grow_with_the_group(spark):
    """Rows of the left-over stage for groups of 200, 400 and 800, in which many members link to nothing."""
    a, b, c = (group_rows(spark, n) for n in (200, 400, 800))
    assert c["members"] > 400
    for kind in ("members", "mine", "theirs", "met"):
        assert b[kind] <= 3 * max(a[kind], 100) and c[kind] <= 3 * max(b[kind], 200), (a, b, c)


def test_frequent_shingles_stay_packed(spark):
    """Shingles that are frequent in a pack come as one row a set, with the same frequencies as row by row."""
    rng = random.Random(8)
    word = lambda: "".join(rng.choices("abcdefghijklmnop", k=7))
    base, rows = [word() for _ in range(80)], []
    for i in range(120):
        w = list(base)
        w[rng.randrange(80)] = word()
        rows.append((i, " ".join(w), "en", "s"))
    docs, cfg = docs_of(spark, [*rows, *((200 + i, *r[1:]) for i, r in enumerate(rows[:50]))]).repartition(4), setjoin.JoinConfig()
    got = []
    for heavy in (cfg.heavy, 10_000):
        with setjoin.Scratch(spark) as keep:
            shared = keep(setjoin.shared_shingles(docs, replace(cfg, heavy=heavy), "text", keep), "test")
            sizes = setjoin.document_sets(docs, cfg, "doc_id", "text").groupBy("fp").agg(F.max("n").alias("n"))
            nodes = {r.fp: (r.n, r.u, set(r.toks), len(r.toks)) for r in setjoin.index_nodes(shared, sizes, cfg).collect()}
            got.append((nodes, shared.filter("often IS NOT NULL").count(), shared.count()))
    assert got[0][0] == got[1][0] and all(len(t) == k for _, _, t, k in got[0][0].values()) and len(got[0][0]) > 100
    assert got[1][1] == 0 and 0 < got[0][1] <= 170 and 3 * got[0][2] < got[1][2]


def test_components_of_a_chain(spark):
    """A shuffled chain of 2,000 nodes, a shorter one, a star and a pair."""
    rng = random.Random(5)
    names = [rng.getrandbits(63) - (1 << 62) for _ in range(2_400)]
    groups = [names[:2_000], names[2_000:2_300], names[2_300:2_398], names[2_398:]]
    pairs = [p for g in (groups[0], groups[1], groups[3]) for p in zip(g[:-1], g[1:], strict=True)] + [(groups[2][0], x) for x in groups[2][1:]]
    rng.shuffle(pairs)
    frame = lambda pairs: spark.createDataFrame([(min(p), max(p)) for p in pairs], "a long, b long")
    with Scratch(spark) as keep:
        got = setjoin.components(frame(pairs), keep).collect()
        assert setjoin.components(frame([]), keep).count() == 0
    assert sorted(map(tuple, got)) == sorted((v, min(g)) for g in groups for v in g)


# --- mixing --------------------------------------------------------------------------------------------------------


def targets_brute(sizes):
    names = sorted((k for k in sizes if k is not None), key=lambda s: [ord(c) for c in s]) + [k for k in sizes if k is None]
    weight = {k: (5, 2, 1)[j % 3] for j, k in enumerate(names)}
    total, stopped = sum(sizes.values()), set()
    while True:
        free = [k for k in names if k not in stopped]
        rest = total - sum(3 * sizes[k] for k in stopped)
        level = rest / sum(weight[k] for k in free) if free else 0
        over = {k for k in free if weight[k] * level > 3 * sizes[k]}
        if not over:
            return {k: 3.0 * sizes[k] if k in stopped else weight[k] * level for k in names}
        stopped |= over


def check_mix(df, tolerance):
    out = mixing.mix_words(df).collect()
    source = {}
    for r in df.collect():
        source.setdefault((r.doc_id, len(WORD.findall(r.text or ""))), r.source)
    sizes = collections.Counter()
    for r in df.collect():
        sizes[r.source] += len(WORD.findall(r.text or ""))
    want, got = targets_brute(sizes), collections.Counter()
    assert len(out) == df.count()
    for r in out:
        s = source[r.doc_id, r.size]
        assert r.source_size == sizes[s] and r.target == pytest.approx(want[s]) and 0 <= r.taken <= 3 * r.size
        got[s] += r.taken
    for s in sizes:
        assert abs(got[s] - want[s]) <= max(2 * 64, tolerance * want[s])
    return sorted((repr(r.doc_id), r.size, r.taken) for r in out)


def test_mixing(docs):
    first = check_mix(docs, 0.02)
    assert first == check_mix(docs.repartition(7), 0.02)


def test_mixing_skew(spark):
    rng = random.Random(1)
    rows = [(k, " ".join(["w"] * rng.randint(0, 200)), "en", rng.choice(["a", "b", "b", "b", "b", "b", "c", None, "", "z"])) for k in range(600)]
    rows += [(1000, "w " * 70_000, "en", "a")] + [(2000 + k, "w " * 3, "en", "tiny") for k in range(2)]
    check_mix(docs_of(spark, rows).repartition(4), 0.02)


def test_mixed_documents(docs, odd, empty):
    for df in (docs, odd):
        taken = {}
        for r in mixing.mix_words(df).collect():
            taken[r.doc_id] = taken.get(r.doc_id, 0) + r.taken
        got = collections.Counter()
        texts = {(r.doc_id, r.text) for r in df.collect()}
        mixed = mixing.mixed_documents(df)
        assert mixed.columns == df.columns
        for r in mixed.collect():
            n = len(WORD.findall(r.text))
            got[r.doc_id] += n
            assert n and r.n_chars == len(r.text)
            own = [WORD.findall(t or "") for i, t in texts if i == r.doc_id]
            assert (r.doc_id, r.text) in texts or any(set(WORD.findall(r.text)) <= set(w) for w in own)
        assert {k: v for k, v in taken.items() if v} == dict(got)
    assert mixing.mix_words(empty).count() == 0 and mixing.mixed_documents(empty).count() == 0


def test_mix_keeps_clashing_columns(spark):
    names = ("__h", "__twin", "__parts", "__words", "__text", "h", "id", "twin", "row", "parts", "new_text", "a.b")
    rows = [(k % 7, f"w{k % 5} " * (20 + k % 5 * 30), "en", "ab"[k % 2], *range(len(names))) for k in range(40)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, " + ", ".join(f"`{n}` long" for n in names)).repartition(3)
    out = mixing.mixed_documents(df)
    assert out.columns == df.columns
    got = out.collect()
    assert got and all(tuple(r)[4:] == tuple(range(len(names))) for r in got)
    assert sum(len(r.text.split()) for r in got) == mixing.mix_words(df).agg(F.sum("taken")).first()[0]


def test_mix_order_and_content(spark):
    """A cut text is a document's words in their order, in runs that begin and end where blocks do."""
    rows = [(k, " ".join(f"d{k}w{j}" for j in range(rng_size)), "en", "abc"[k % 3]) for k, rng_size in enumerate([500, 10, 64, 129, 7, 300, 1000, 65, 90])]
    df = docs_of(spark, rows).repartition(2)
    texts = {i: t.split() for i, t, _, _ in rows}
    seen = collections.Counter()
    for r in mixing.mixed_documents(df).collect():
        words = [int(w.split("w")[1]) for w in r.text.split()]
        assert all(w.startswith(f"d{r.doc_id}w") for w in r.text.split()) and words == sorted(set(words))
        assert r.text in " ".join(texts[r.doc_id]) or len(words) < len(texts[r.doc_id])
        seen[r.doc_id] += len(words)
    assert {k: v for k, v in seen.items() if v} == {r.doc_id: r.taken for r in mixing.mix_words(df).collect() if r.taken}


def test_shards(spark, docs):
    """Counts of many shards: multinomial draws, settled to the targets; blocks by shard hold the words that are taken."""
    cfg = mixing.MixConfig(shard_slots=64, block=16)
    d, facts = mixing.plan(mixing.packed(docs, cfg), cfg)
    k = {r.s: r.k for r in facts.collect()}
    deck = sum(k.values())
    drawn = collections.Counter()
    shards: dict = {}
    for r in mixing.drawn_counts(facts, cfg).collect():
        drawn[r.s] += r.drawn
        shards.setdefault(r.shard, {})[r.s] = r.drawn
    assert len(shards) == -(-deck // 64) > 20 and all(sum(c.values()) == 64 for j, c in shards.items() if j < deck // 64)
    for s, n in k.items():  # mean and variance of a shard's count of a source
        p = n / deck
        own = np.array([c.get(s, 0) for j, c in shards.items() if j < deck // 64])
        assert abs(own.mean() - 64 * p) < 5 * (64 * p * (1 - p) / len(own)) ** 0.5 + 1e-9
        assert own.var() < 64 * p * (1 - p) * (1 + 6 * (2 / len(own)) ** 0.5) + 0.1
    big = max(k, key=k.get)
    assert np.var([c.get(big, 0) for c in shards.values()]) > 0
    spans: dict = {}
    for r in mixing.shard_counts(facts, cfg).collect():
        spans.setdefault(r.s, []).append((r.shard, r.before, r["count"]))
        late = r.shard >= len(shards)
        assert late or r["count"] <= shards[r.shard][r.s]
    for s, n in k.items():
        at = 0
        for _, before, count in sorted(spans.get(s, [])):
            assert before == at and count > 0
            at += count
        assert at == n
    mix = mixing.slots(facts, cfg).collect()
    assert len(mix) == deck == len({(r.shard, r.place) for r in mix}) == len({(r.s, r.block, r["pass"]) for r in mix})
    assert {r.s for r in mix if r.shard == 0} == set(shards[0])
    got = mixing.shard_blocks(docs, cfg).collect()
    assert {(r.shard, r.place) for r in got} == {(r.shard, r.place) for r in mix} and len(got) == len(mix)
    assert sum(len(r.words) for r in got) == mixing.mix_words(docs, cfg).agg(F.sum("taken")).first()[0]
    vocabulary = {w for r in docs.collect() for w in WORD.findall(r.text or "")}
    assert all(w in vocabulary for r in got for w in r.words) and max(len(r.words) for r in got) == 16


def test_shuffle_is_a_permutation(spark):
    for n in (1, 2, 7, 1000):
        k = spark.range(n).select(mixing.shuffled(F.col("id"), F.lit(n).cast("long"), [F.lit("s"), F.lit(3)], mixing.MixConfig()).alias("k"))
        assert sorted(r.k for r in k.collect()) == list(range(n))


# --- models --------------------------------------------------------------------------------------------------------


def held(i):
    return zlib.crc32(str(i).encode()) % 4 == 2


def test_toxicity(spark):
    sf = "/root/testdata/sf0.1"
    lab = {r.doc_id: r.toxic for r in registry.table(spark, sf, "labels").collect()}
    out = registry.op4_toxicity(spark, sf).collect()
    assert all(r.held_out == held(r.doc_id) and 0 <= r.score <= 1 and r.predicted == int(r.score >= 0.3) for r in out)
    test = [(r.predicted, lab[r.doc_id]) for r in out if r.held_out and r.doc_id in lab]
    hit = sum(p and y for p, y in test)
    assert hit / sum(y for _, y in test) > 0.6 and hit / sum(p for p, _ in test) > 0.75


def test_subwords_share_misspellings():
    cfg = toxicity.ToxicConfig()
    a, b, c = (set(toxicity.subwords(w, cfg)) for w in ("stupid", "stuupid", "garden"))
    assert len(a & b) > len(a & c)


def test_language(spark, rows, docs):
    out = {r.doc_id: r for r in langid.identify(docs, langid.fit(docs)).collect()}
    test = [r for r in rows if held(r.doc_id)]
    assert sum(out[r.doc_id].lang_pred == r.lang for r in test) / len(test) > 0.9
    assert {r.lang_pred for r in out.values()} <= {"en", "de", "fr", "es", "und"}


def test_language_brute_force(docs, rows):
    """Each prediction is the language whose dictionary compresses the text's parts to the fewest bytes."""
    import zstandard as z

    cfg = langid.LangConfig()
    dicts = langid.fit(docs, cfg)
    out = {r.doc_id: r for r in langid.identify(docs, dicts, cfg).collect()}
    for r in rows[:60]:
        raw = (r.text or "").lower().encode("utf-8", "replace")
        if not any(c.isalpha() for c in r.text or ""):
            continue
        size = {}
        for lang in sorted(dicts):
            d = z.ZstdCompressionDict(dicts[lang], dict_type=z.DICT_TYPE_RAWCONTENT)
            c = z.ZstdCompressor(level=cfg.level, dict_data=d, write_content_size=False, write_checksum=False, write_dict_id=False)
            size[lang] = sum(len(c.compress(raw[i : i + cfg.part_bytes])) for i in range(0, len(raw), cfg.part_bytes))
        best, *more = sorted(size.values())
        assert out[r.doc_id].lang_pred == min(size, key=lambda k: (size[k], k))
        gap = (more[0] - best) / best
        assert out[r.doc_id].score == pytest.approx(min(1.0, 0.5 + gap / 2)) and out[r.doc_id].narrow == (gap < cfg.margin)


def test_many_languages_and_long_texts(spark):
    """300 languages are all learned, one of which has long texts only; more than the bound is an error."""
    rng = random.Random(3)
    rows, i = [], 0
    for k in range(300):
        words = ["".join(rng.choices("abcdefghijklmnopqrstuvwxyz", k=rng.randint(2, 7))) for _ in range(40)]
        for _ in range(3):
            i += 1
            rows.append((i, " ".join(rng.choices(words, k=3000 if k == 7 else 60)), f"l{k:03d}", "s"))
    df = docs_of(spark, rows)
    dicts = langid.fit(df)
    train = {lang for i, _, lang, _ in rows if not held(i)}
    assert set(dicts) == train and len(train) > 290 and "l007" in train
    some = [r for r in rows if r[2] in train][:24]
    got = {r.doc_id: r.lang_pred for r in langid.identify(docs_of(spark, some), dicts).collect()}
    assert sum(got[i] == lang for i, _, lang, _ in some) >= 23
    with pytest.raises(ValueError, match="languages"):
        langid.fit(df, langid.LangConfig(max_langs=100))


def test_toxicity_gradient():
    """A training step moves table and softmax along the numeric gradient of the softmax loss of averaged subwords."""
    cfg = toxicity.ToxicConfig(log2_rows=8, dim=3)
    texts, y = ["bad words here bad", "good day to all", "worse words"], np.array([1, 0, 1])
    make = lambda: toxicity.Trainer(texts, y.tolist(), cfg)
    t = make()
    t.table, t.out, t.bias = t.table.astype(np.float64), t.out.astype(np.float64), t.bias.astype(np.float64)
    names = list(dict.fromkeys(w for x in texts for w in x.split()))

    def loss(table, out, bias):
        total = 0.0
        for text, label in zip(texts, y, strict=True):
            words = text.split()
            # a word's repeats inside a window count in the length only
            x = sum(table[toxicity.subwords(w, cfg)].mean(0) for w in dict.fromkeys(words)) / len(words)
            z = x @ out + bias
            total += np.log(np.exp(z - z.max()).sum()) + z.max() - z[label]
        return total / len(texts)

    assert len(names) == len(t.size)
    before = [a.copy() for a in (t.table, t.out, t.bias)]
    t.table_sq, t.out_sq, t.bias_sq = (np.full(a.shape, 1e30) for a in (t.table_sq, t.out_sq, t.bias_sq))  # AdaGrad becomes a plain small step
    t.step(t.docs, y)
    for k, now in enumerate((t.table, t.out, t.bias)):
        moved = (before[k] - now) / (cfg.rate / 1e15)
        for _ in range(25):
            at = tuple(np.random.default_rng(_).integers(0, n) for n in now.shape)
            probe = []
            for step in (1e-6, -1e-6):
                changed = [a.copy() for a in before]
                changed[k][at] += step
                probe.append(loss(*changed))
            assert moved[at] == pytest.approx((probe[0] - probe[1]) / 2e-6, abs=0.05, rel=0.05)


def test_model_edges(spark, odd, empty):
    labels = spark.createDataFrame([(5, 1), (6, 0), (4, None)], "doc_id long, toxic int")
    for df, n in ((odd, len(odd_rows())), (empty, 0)):
        assert toxicity.score(df, toxicity.fit(df, labels)).count() == n
        assert langid.identify(df, langid.fit(df)).count() == n
    pred = {r.doc_id: r.lang_pred for r in langid.identify(odd, langid.fit(odd)).collect()}
    assert pred[1] == pred[2] == pred[3] == "und"


# --- tokens --------------------------------------------------------------------------------------------------------

HARD = [" ", "  ", "\n", "\t", "a", "Bc", "'s", "'re", "<|endoftext|>", "é", "1", "½", "٣", "\xa0", "\u3000", "\x85", "\x1c", "\u200b", "日本", "👍🏽", ".", "!!", ",", "_", "é", "\r\n", "ǅ", "Ⅷ", "the", "ing", "\x00"]


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(registry.tokenizer_path())


def hard_texts():
    rng = random.Random(9)
    return ["".join(rng.choices(HARD, k=rng.randint(0, 25))) for _ in range(3000)]


def test_counts_equal_library(rows, library):
    c = bpe_count.Counter(*bpe_count.load_merges(registry.tokenizer_path()))
    texts = [r.text for r in rows] + hard_texts()
    assert [c.count(t) for t in texts] == [len(e.ids) for e in library.encode_batch(texts, add_special_tokens=False)]


def test_count_edges(odd, empty):
    out = {r.doc_id: r for r in bpe_count.token_counts(odd, registry.tokenizer_path(), limit=2).collect()}
    assert (out[1].n_bytes, out[1].n_tokens, out[1].over_limit) == (0, 0, False) and out[6].over_limit
    assert bpe_count.token_counts(empty, registry.tokenizer_path()).count() == 0


def test_encoder_equals_library(rows, library):
    with open(registry.tokenizer_path()) as f:
        e = token_files.Encoder(f.read(), 0)
    texts = [None, "", *(r.text for r in rows), *hard_texts()]
    ids, at = np.concatenate([x for x, _ in e.encode(pa.array(texts, pa.string()), 100)]), 0
    sizes = np.concatenate([n for _, n in e.encode(pa.array(texts, pa.string()), 100)])
    for n, enc in zip(sizes, library.encode_batch([t or "" for t in texts], add_special_tokens=False), strict=True):
        assert ids[at : at + n].tolist() == enc.ids + [0]
        at += n


def test_rans_round_trip():
    rng = np.random.default_rng(1)
    cfg = rans.RansConfig(block_tokens=5000, lanes=32, checkpoint_rows=16)
    for n in (0, 1, 63, 20_011):
        ids = (rng.zipf(1.3, n) % 50257).astype(np.uint32)
        blob = rans.encode_segment([3, None, -7], [n, 0, 0], ids, cfg)
        s = rans.Segment(blob)  # a reader needs no settings of the writer
        assert s.doc_ids == [3, None, -7] and (s.ids() == ids).all()
        for b, (m, w, marks, *_) in enumerate(s.blocks):
            for c in range(marks + 1):
                assert (s.block(b, c) == ids[5000 * b : 5000 * b + m][c * 16 * w :]).all()
    bad = bytearray(blob)
    bad[-1] ^= 1
    with pytest.raises(ValueError, match="damaged"):
        rans.Segment(bytes(bad)).ids()
    bad = bytearray(blob)
    bad[60] ^= 1
    with pytest.raises(ValueError):
        rans.Segment(bytes(bad))
    with pytest.raises(ValueError, match="does not end"):
        rans.decode_rows(np.full(4, rans.LOW + np.uint64(1), np.uint64), np.zeros(0, np.uint32), 0, 0, (None, None, None), 14)


def token_brute(rows, library):
    at, out = 0, []
    for i, t in sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1] is not None, r[1] or "")):
        ids = np.array(library.encode(t or "", add_special_tokens=False).ids + [0], "<u4")
        out.append((i, at, len(ids), zlib.crc32(ids.tobytes())))
        at += len(ids)
    return out


def test_token_files(spark, docs, rows, odd, empty, library):
    for df, have in ((docs, [(r.doc_id, r.text) for r in rows]), (odd, [(i, t) for i, t, _, _ in odd_rows()])):
        for size in (2_000_000, 5000):
            got = token_files.round_trip(df, registry.tokenizer_path(), segment_tokens=size).collect()
            assert sorted(map(tuple, got), key=lambda r: r[1]) == token_brute(have, library)
    assert token_files.round_trip(empty, registry.tokenizer_path()).count() == 0


# --- spans ---------------------------------------------------------------------------------------------------------


def units_brute(text, long):
    """Sentences from the characters alone: they end after white space that follows a mark, or after a line end."""
    white, out, at, i = " \t\n\x0b\x0c\r", [], 0, 0
    while i < len(text):
        if text[i] in white and (text[i] == "\n" or (i and text[i - 1] in ".!?")):
            while i < len(text) and text[i] in white:
                i += 1
            out.append(text[at:i])
            at = i
        else:
            i += 1
    out.append(text[at:])
    cut = []
    for u in filter(None, out):
        words = list(WORD.finditer(u))
        if len(u.lower().split()) <= long:
            cut.append(u)
            continue
        at = 0
        for m, nxt in zip(words, words[1:], strict=False):
            if zlib.crc32(m[0].lower().encode("utf-8", "replace")) % 6 == 0:
                cut.append(u[at : nxt.start()])
                at = nxt.start()
        cut.append(u[at:])
    return cut


def spans_brute(rows, cfg):
    """Every run of sentences of every document against all runs before it, by their words."""
    seen, out = {}, {}
    for i, t in rows:
        u = [tuple(x.lower().split()) for x in units_brute(t or "", cfg.long)]
        gone = set()
        for a in range(len(u)):
            if not u[a]:
                continue
            for b in range(a + 1, len(u) + 1):
                if sum(bool(x) for x in u[a:b]) >= cfg.sentences and sum(map(len, u[a:b])) >= cfg.least_words:
                    run = tuple(w for x in u[a:b] for w in x)
                    if run in seen:
                        gone |= set(range(a, b))
                    seen.setdefault(run, i)
                    break
        out[i] = len(gone)
    return out


def test_spans(docs, rows):
    small = [r for r in rows if len(r.text or "") < 30_000]
    ids = [r.doc_id for r in small]
    some = docs.filter(F.col("doc_id").isin(ids))
    for cfg in (sentence_spans.SpanConfig(), sentence_spans.SpanConfig(sentences=3, least_words=5, long=40)):
        out = {r.doc_id: r for r in sentence_spans.remove_repeats(some, cfg).collect()}
        assert {i: r.n_removed for i, r in out.items()} == spans_brute([(r.doc_id, r.text) for r in small], cfg)
        assert sum(r.n_removed > 0 for r in out.values()) > 5
    for r in small:
        o, at, left = out[r.doc_id], 0, []
        for s in o.removed:
            left.append(r.text[at : s.begin])
            at = s.end
        assert "".join([*left, r.text[at:]]) == o.text


def test_planted_passage(spark):
    rng = random.Random(2)
    sentence = lambda: " ".join("".join(rng.choices("abcdefghij", k=6)) for _ in range(rng.randint(4, 12))) + "."
    passage = " ".join(sentence() for _ in range(8))
    rows = [(k, " ".join([sentence() for _ in range(9)] + ([passage] if k % 3 == 0 else []) + [sentence() for _ in range(4)]), "en", "s") for k in range(30)]
    out = {r.doc_id: r for r in sentence_spans.remove_repeats(docs_of(spark, rows)).collect()}
    inner = " ".join(passage.split(". ")[2].split())
    for k in range(30):
        assert (out[k].n_removed > 0) == (k % 3 == 0 and k > 0)
        assert (inner in out[k].text) == (k == 0)


def test_passage_inside_sentences(spark):
    """A passage of 55 words that is pasted into the middle of sentences, with few marks of its own."""
    rng = random.Random(8)
    words = lambda n: " ".join("".join(rng.choices("abcdefghij", k=6)) for _ in range(n))
    passage = words(55)
    rows = [(k, words(15) + ". " + words(7) + (" " + passage if k % 2 else "") + " " + words(9) + ". " + words(12) + ".", "en", "s") for k in range(12)]
    out = {r.doc_id: r.n_removed for r in sentence_spans.remove_repeats(docs_of(spark, rows)).collect()}
    assert {k for k, n in out.items() if n} == {3, 5, 7, 9, 11}


def test_span_edges(odd, empty):
    out = sentence_spans.remove_repeats(odd).collect()
    assert len(out) == len(odd_rows()) and sentence_spans.remove_repeats(empty).count() == 0
    assert {r.doc_id: r.text for r in out}[1] is None


def test_sentence_bounds_cover():
    for t in ("", "a", "A b. C d!  E\n\nf", "\n\n x", "no end. "):
        b = sentence_spans.sentence_bounds(t)
        assert "".join(t[x:y] for x, y in b) == t


# --- benchmark -----------------------------------------------------------------------------------------------------

CLEAN = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def leaks_brute(docs, items):
    words = lambda t: CLEAN.findall((t or "").translate(LOWER))
    windows = {}
    for i, t in items:
        w = words(t)
        for k in range(max(1, len(w) - 9) if w else 0):
            windows.setdefault(tuple(w[k : k + 10]), set()).add(i)
    sizes = {len(x) for x in windows}
    out = []
    for i, t in docs:
        w, hit, found = words(t), set(), set()
        for n in sizes:
            for k in range(len(w) - n + 1):
                got = windows.get(tuple(w[k : k + n]))
                if got:
                    hit |= set(range(k, k + n))
                    found |= got
        sha = hashlib.sha256(",".join(sorted(str(x) for x in found if x is not None)).encode()).hexdigest()
        out.append((i, len(w), len(hit), len(found), sha, bool(hit)))
    return sorted(out, key=repr)


def test_contamination(spark, small, docs, rows, odd, empty):
    bench = registry.table(spark, small, "benchmark")
    items = [(r.item_id, r.text) for r in bench.collect()]
    want = leaks_brute([(r.doc_id, r.text) for r in rows], items)
    assert sum(r[5] for r in want) > 0
    found = decontaminate.benchmark_windows(bench, 10)
    many = found.agg(F.sum("n")).first()[0] // 3
    assert decontaminate.blocks_of(found, many) > 5 and decontaminate.blocks_of(found, 10**9) == 1
    for limit in (decontaminate.MAX_NODES, many):  # one automaton, then many blocks
        assert sorted(map(tuple, decontaminate.contamination(docs, bench, max_nodes=limit).collect()), key=repr) == want
    clean = {r[0] for r in want if not r[5]}
    for limit in (decontaminate.MAX_NODES, many):
        assert {r.doc_id for r in decontaminate.drop_contaminated(docs, bench, max_nodes=limit).collect()} == clean
    few = spark.createDataFrame([(1, None), (2, "..."), (3, "The CAT"), (3, "sat on"), (4, "ÉTÉ ½"), (None, "the mat"), (None, "it was"), (None, None)], "item_id long, text string")
    for df, have in ((odd, [(i, t) for i, t, _, _ in odd_rows()]), (empty, [])):
        for limit in (decontaminate.MAX_NODES, 4):
            assert sorted(map(tuple, decontaminate.contamination(df, few, max_nodes=limit).collect()), key=repr) == leaks_brute(have, [(r.item_id, r.text) for r in few.collect()])
    assert decontaminate.contamination(odd, few.limit(0)).filter("contaminated").count() == 0


def test_cut_keeps_offsets():
    s = decontaminate.Scanner.of([(1, "alpha beta gamma")], 10)
    assert s.cut("Été — Alpha,  BETA/gamma! end") == "Été — ! end"
    assert s.original_spans("nothing here") == []


# --- urls ----------------------------------------------------------------------------------------------------------


def url_brute(url):
    if not url or "://" not in url:
        return "", "", None
    rest = url.split("://", 1)[1]
    host = re.split(r"[/?#]", rest, maxsplit=1)[0]
    path = re.split(r"[?#]", rest[len(host) :], maxsplit=1)[0]
    host = host.translate(LOWER)
    fits = [r for r in registry.URL_RULES if (host == r.host or host.endswith("." + r.host)) and path.startswith(r.path)]
    return host, path, max(fits, key=lambda r: len(r.name)) if fits else None


def test_urls(spark, small):
    pages = registry.table(spark, small, "pages").select("page_id", "url", "html")
    more = [(10_000 + k, u, "") for k, u in enumerate([None, "", "x", "a://b", "HTTP://WWW.Example.COM/en/7?x#y", "http://example.net?/de/8", "http://com/en/x", "q\nr://s/es/", "http://a.org/es/#/", "://h/p"])]
    pages = pages.unionByName(spark.createDataFrame(more, "page_id long, url string, html string"))
    have = {r.page_id: r.url for r in pages.collect()}
    out = url_rules.judge_urls(pages, registry.URL_RULES).collect()
    assert len(out) == len(have)
    for r in out:
        host, path, rule = url_brute(have[r.page_id])
        assert (r.host, r.path, r.rule) == (host, path, rule.name if rule else None)
        assert r.verdict == rule.verdict if rule else r.verdict in ("allow", "block")
    assert url_rules.judge_urls(pages.limit(0), registry.URL_RULES).count() == 0


def test_propagation_equals_iteration(spark):
    rng = random.Random(4)
    hosts = [f"h{k}" for k in range(12)]
    links = {(a, b): rng.randint(1, 3) for a in hosts[:9] for b in rng.sample(hosts, 3) if a != b}
    seed = {h: (float(k == 0), float(k in (5, 6))) for k, h in enumerate(hosts)}
    seeds = spark.createDataFrame([(h, *s) for h, s in seed.items()], "host string, trust double, distrust double")
    edges = spark.createDataFrame([(a, b, n) for (a, b), n in links.items()], "src string, dst string, n long")
    got = {r.host: (r.trust, r.distrust) for r in url_rules.propagate(seeds, edges, url_rules.RankConfig(tolerance=1e-3)).collect()}
    outs, ins = collections.Counter(), collections.Counter()
    for (a, b), n in links.items():
        outs[a] += n
        ins[b] += n
    t, d = ({h: s[k] for h, s in seed.items()} for k in (0, 1))
    linked = set(outs) | set(ins)
    while True:
        nt = {h: 0.15 * seed[h][0] + 0.85 * (sum(t[a] * n / outs[a] for (a, b), n in links.items() if b == h) + (0 if outs[h] else t[h])) for h in linked}
        nd = {h: 0.15 * seed[h][1] + 0.85 * (sum(d[b] * n / ins[b] for (a, b), n in links.items() if a == h) + (0 if ins[h] else d[h])) for h in linked}
        moved = max(max(abs(nt[h] - t[h]), abs(nd[h] - d[h])) for h in linked)
        t, d = t | nt, d | nd
        if moved < 1e-12:
            break
    for h in hosts:
        assert got[h] == pytest.approx((t[h], d[h]), abs=0.01)  # the last move, 0.001, over 1 - 0.85


def test_propagation_reaches_far_hosts(spark):
    """A chain of 40 hosts: trust flows to its end, whatever its length."""
    seeds = spark.createDataFrame([("h0", 1.0, 0.0)], "host string, trust double, distrust double")
    edges = spark.createDataFrame([(f"h{k}", f"h{k + 1}", 1) for k in range(40)], "src string, dst string, n long")
    got = {r.host: r.trust for r in url_rules.propagate(seeds, edges, url_rules.RankConfig(tolerance=1e-4)).collect()}
    for k in range(40):
        assert got[f"h{k}"] == pytest.approx(0.15 * 0.85**k, abs=1e-7)
    assert got["h40"] > 0


def test_links_between_hosts(spark):
    html = """<a href="http://B.org/x">1</a> <a HREF='//c.org'>2</a> <a href="/own">3</a> <a href=https://a.org/>self</a> <a href="mailto:x@y">m</a>"""
    pages = spark.createDataFrame([("a.org", html), ("a.org", None), ("", html)], "host string, html string")
    assert sorted(map(tuple, url_rules.host_edges(pages).collect())) == [("a.org", "b.org", 1), ("a.org", "c.org", 1)]


def test_verdicts_of_linked_hosts(spark):
    """Links to a blocked host do not free it, and links to a linker change neither its verdict nor its scores."""
    rules = [*(url_rules.Rule(h, "/bad/", "block") for h in ("spam.org", "spam.net", "spam.biz")), url_rules.Rule("good.org", "/", "allow")]
    to = lambda *hosts: " ".join(f'<a href="http://{h}/">x</a>' for h in hosts)

    def judged(links):
        pages = [(f"http://{h}/{'bad/' * (k > 0 and h.startswith('spam'))}{k}", html) for h, html in links.items() for k in range(5)]
        df = spark.createDataFrame([(k, u, t) for k, (u, t) in enumerate(pages)], "page_id long, url string, html string")
        return {r.host: r for r in url_rules.judge_urls(df, rules).collect() if r.path == "/0"}

    links = {"spam.org": "", "spam.net": "", "spam.biz": to(*(f"d{k}.org" for k in range(9))), "a.org": to("spam.org", "spam.net"), "big.org": to("spam.org", *(f"c{k}.org" for k in range(30))), "good.org": to("a.org")}
    one, more = judged(links), judged(links | {"b.org": to("a.org"), "c.org": to("spam.biz")})
    for out in (one, more):
        assert all(out[h].verdict == ("block" if h.startswith("spam") else "allow") for h in out if h != "a.org")
        assert all(0 <= x <= 1 + 1e-9 for r in out.values() for x in (r.trust, r.distrust))
    assert one["a.org"].verdict == more["a.org"].verdict and one["a.org"].distrust == pytest.approx(more["a.org"].distrust, abs=1e-3)
    assert one["a.org"].distrust > 0.35 > one["big.org"].distrust
