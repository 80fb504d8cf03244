"""Quality rules: base counts, and divergence from language references.

Each whole text gives two histograms: characters by class, and common words of a language (its function words
plus one cell for all other words). References are the same histograms summed over all documents of a language;
languages without a fixed list of common words learn theirs from the same documents. A text whose Jensen-Shannon
distance (square root of the divergence, base 2, so 0 to 1) to its own language's reference and to those of the
fixed languages is above a limit is rejected; a text below a minimum length, or of a language without a reference,
is never judged by a histogram (guard), because a short text's histogram says little.

Edge cases: null or empty texts have no words, so the base rule rejects them. Rows are independent, so repeated
rows get equal verdicts. Null and empty languages have no reference: only the base rules judge their texts. A language
with few documents has a reference near each of them, which rejects little.
An empty table gives no references and no rows.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .texts import filter_rows, map_texts

#: Common words of the fixed languages (fixed values).
COMMON = {
    "en": "the of and to in a is that for it as was with be by on not he his but at are this have from or had an they which one you were all her she there would their we him been has when who will no more if out so up what".split(),
    "fr": "de la le et les des en un une du que est pour qui dans a par plus pas au sur ne se ce il sont ou avec son aux elle ses mais comme on cette nous ont sa leur été être vous".split(),
    "de": "der die und in den von zu das mit sich des auf für ist im dem nicht ein eine als auch es an werden aus er hat dass sie nach wird bei einer um am sind noch wie einem über so zum war haben nur oder aber".split(),
    "es": "de la que el en y a los se del las un por con no una su para es al lo como más o pero sus le ha me si sin sobre este ya entre cuando todo esta ser son dos también fue había era muy".split(),
}
LANGS = sorted(COMMON)
WORD_CELLS = {w: i for i, w in enumerate(sorted({w for ws in COMMON.values() for w in ws}))}
OTHER_WORD = len(WORD_CELLS)
#: Common words that another language learns.
LEARNED_WORDS = 60
#: Character classes: space, lower, upper, digit, punctuation, symbol, other ASCII, beyond ASCII.
CLASSES = 8
SYMBOLS = b"#*$%&|<>"
SPACES = b" \t\n\x0b\x0c\r"


def class_of_byte() -> np.ndarray:
    """Class of each lead byte; continuation bytes get class 8, which is dropped."""
    out = np.full(256, 6)
    for b in range(256):
        c = chr(b)
        if b >= 0xC0:
            out[b] = 7
        elif b >= 0x80:
            out[b] = 8
        elif b in SPACES:
            out[b] = 0
        elif c.islower():
            out[b] = 1
        elif c.isupper():
            out[b] = 2
        elif c.isdigit():
            out[b] = 3
        elif b in SYMBOLS:
            out[b] = 5
        elif 33 <= b <= 126:
            out[b] = 4
    return out


CLASS = class_of_byte()


@dataclass(frozen=True)
class QualityRules:
    min_words: int = 50
    max_repeat_percent: int = 50
    #: Guards: fewer characters or words than this and the histogram does not judge.
    min_chars: int = 200
    min_hist_words: int = 150
    max_class_distance: float = 0.30
    max_word_distance: float = 0.28


def class_counts(raw: bytes) -> tuple[np.ndarray, np.ndarray]:
    """How often each byte comes, and each character class."""
    bytes_ = np.bincount(np.frombuffer(raw, np.uint8), minlength=256)
    return bytes_, np.bincount(CLASS, weights=bytes_, minlength=9)[:CLASSES]


def word_counts(words: Iterable[tuple[bytes, int]], own: dict[str, int] | None) -> tuple[np.ndarray, np.ndarray | None]:
    """Common-word histogram of (word, times), and that of learned words ``own``."""
    common = np.zeros(OTHER_WORD + 1)
    learned = None if own is None else np.zeros(len(own) + 1)
    for w, times in words:
        word = w.lower().decode("utf-8", "replace")
        common[WORD_CELLS.get(word, OTHER_WORD)] += times
        if learned is not None:
            learned[own.get(word, -1)] += times
    return common, learned


def features(text: str | None, own: dict[str, int] | None = None) -> tuple[list[int], np.ndarray, np.ndarray, np.ndarray | None]:
    """Base counts, class histogram and common-word histogram of one whole text, and that of learned words ``own``."""
    raw = (text or "").encode("utf-8", "replace")
    bytes_, classes = class_counts(raw)
    words = raw.split()  # bytes split at exactly the six separators
    n = len(words)
    lines = [x for x in raw.split(b"\n") if x.strip()]
    ids: dict[bytes, int] = {}
    seq = np.fromiter((ids.setdefault(w, len(ids)) for w in words), np.int64, n)
    repeat = 0
    if n >= 3 and len(ids) < n:
        v = len(ids)
        if v < 2_000_000:
            _, inverse, times = np.unique((seq[:-2] * v + seq[1:-1]) * v + seq[2:], return_inverse=True, return_counts=True)
        else:  # the packed key of three would overflow
            _, inverse, times = np.unique(np.stack([seq[:-2], seq[1:-1], seq[2:]], 1), axis=0, return_inverse=True, return_counts=True)
        often = times[inverse.reshape(-1)] > 1
        hit = np.zeros(n, bool)
        for k in range(3):
            hit[k : n - 2 + k] |= often
        repeat = int(hit.sum())
    common, learned = word_counts(zip(ids, np.bincount(seq, minlength=len(ids)), strict=True), own)
    chars = int(bytes_.sum() - bytes_[0x80:0xC0].sum())
    base = [n, chars - int(classes[0]), int(classes[5]), len(lines) - len(set(lines)), repeat]
    return base, classes, common, learned


def js_distance(p: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Jensen-Shannon distance of each row of counts ``p`` to the counts ``q``."""
    p = p / np.maximum(p.sum(1, keepdims=True), 1)
    q = q / max(q.sum(), 1)
    m = (p + q) / 2

    def half(x):
        with np.errstate(divide="ignore", invalid="ignore"):
            return np.where(x > 0, x * np.log2(np.where(x > 0, x, 1) / np.where(m > 0, m, 1)), 0).sum(1)

    return np.sqrt(np.clip((half(np.broadcast_to(q, p.shape)) + half(p)) / 2, 0, 1))


def learned_words(docs: DataFrame, text_col: str, lang_col: str) -> dict[str, list[str]]:
    """The most frequent words of each language beside the fixed ones, over all its documents."""
    lang = F.col(lang_col)
    others = docs.filter(lang.isNotNull() & (lang != "") & ~lang.isin(LANGS))
    if not others.select(lang_col).limit(1).count():
        return {}

    def make():
        def rows(texts, langs):
            out: dict[tuple[str, str], int] = {}
            for t, of in zip(texts, langs, strict=True):
                for w in (t or "").encode("utf-8", "replace").split():
                    key = of, w.lower().decode("utf-8", "replace")
                    out[key] = out.get(key, 0) + 1
            return [(of, w, n) for (of, w), n in out.items()]

        return rows

    counts = map_texts(others, [text_col, lang_col], make, "lang string, word string, n long").groupBy("lang", "word").agg(F.sum("n").alias("n"))
    top = counts.withColumn("k", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "word"))).filter(F.col("k") <= LEARNED_WORDS)
    out: dict[str, list[str]] = {}
    for r in top.select("lang", "word").collect():  # a fixed number of words of each language
        out.setdefault(r.lang, []).append(r.word)
    return {of: sorted(ws) for of, ws in out.items()}


def cells_of(words: list[str] | None) -> dict[str, int] | None:
    return None if words is None else {w: i for i, w in enumerate(words)}


def references(docs: DataFrame, text_col: str = "text", lang_col: str = "lang") -> dict[str, dict[str, list]]:
    """{language: {'classes': counts, 'words': counts}} over all documents, with 'own' (its common words) if learned;
    its size depends on the number of languages alone."""
    own = learned_words(docs, text_col, lang_col)

    def make():
        cells = {lang: cells_of(ws) for lang, ws in own.items()}

        def rows(texts, langs):
            out = {}
            for t, lang in zip(texts, langs, strict=True):
                if t and (lang in COMMON or lang in cells):
                    raw = t.encode("utf-8", "replace")
                    _, c = class_counts(raw)
                    w, mine = word_counts(Counter(raw.split()).items(), cells.get(lang))
                    w = w if mine is None else mine
                    a = out.setdefault(lang, np.zeros(CLASSES + len(w)))
                    a[:CLASSES] += c
                    a[CLASSES:] += w
            return [(lang, i, int(x)) for lang, a in out.items() for i, x in enumerate(a) if x]

        return rows

    cells = map_texts(docs, [text_col, lang_col], make, "lang string, cell int, n long").groupBy("lang", "cell").agg(F.sum("n").alias("n"))
    refs = {}
    for r in cells.collect():  # at most a fixed number of cells of each language
        refs.setdefault(r.lang, np.zeros(CLASSES + (len(own[r.lang]) if r.lang in own else OTHER_WORD) + 1))[r.cell] = r.n
    return {lang: {"classes": a[:CLASSES].tolist(), "words": a[CLASSES:].tolist()} | ({"own": own[lang]} if lang in own else {}) for lang, a in refs.items()}


def judge(texts: list[str | None], refs: dict, rules: QualityRules, langs: list[str | None] | None = None) -> list[tuple]:
    """(n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, class_js, word_js, kept) of each text."""
    if not texts:
        return []
    langs = [None] * len(texts) if langs is None else langs
    learned = {lang: cells_of(refs[lang]["own"]) for lang in set(langs) if lang in refs and "own" in refs[lang]}
    made = [features(t, learned.get(lang)) for t, lang in zip(texts, langs, strict=True)]
    classes, words = np.stack([m[1] for m in made]), np.stack([m[2] for m in made])
    far = np.ones((2, len(texts)))
    for lang, r in sorted(refs.items()):
        if "own" not in r:
            far[0] = np.minimum(far[0], js_distance(classes, np.array(r["classes"])))
            # only the cells of the language's own common words count; all others join the last cell
            own = [WORD_CELLS[w] for w in COMMON[lang]]
            q = np.array(r["words"])
            fold = lambda x: np.concatenate([x[..., own], (x.sum(-1) - x[..., own].sum(-1))[..., None]], -1)  # noqa: B023, E731
            far[1] = np.minimum(far[1], js_distance(fold(words), fold(q)))
        elif lang in learned:
            at = [k for k, x in enumerate(langs) if x == lang]
            far[0, at] = np.minimum(far[0, at], js_distance(classes[at], np.array(r["classes"])))
            far[1, at] = np.minimum(far[1, at], js_distance(np.stack([made[k][3] for k in at]), np.array(r["words"])))
    out = []
    for k, (base, c, _, _) in enumerate(made):
        n, repeat = base[0], base[4]
        failed = n < rules.min_words or 100 * repeat > rules.max_repeat_percent * n
        cj = round(float(far[0, k]), 6) if langs[k] in refs and c.sum() >= rules.min_chars else None
        wj = round(float(far[1, k]), 6) if langs[k] in refs and n >= rules.min_hist_words else None
        odd = (cj is not None and cj > rules.max_class_distance) or (wj is not None and wj > rules.max_word_distance)
        out.append((*base, failed, cj, wj, not failed and not odd))
    return out


def assess(docs: DataFrame, rules: QualityRules = QualityRules(), refs: dict | None = None, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """Counts, distances and verdict of each row."""
    refs = references(docs, text_col, lang_col) if refs is None else refs

    def make():
        return lambda ids, texts, langs: [(i, *r) for i, r in zip(ids, judge(texts, refs, rules, langs), strict=True)]

    schema = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, class_js double, word_js double, kept boolean"
    return map_texts(docs, [id_col, text_col, lang_col], make, schema)


def keep_good(docs: DataFrame, rules: QualityRules = QualityRules(), refs: dict | None = None, text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """The rows that pass, with all their columns; narrow, no join."""
    refs = references(docs, text_col, lang_col) if refs is None else refs
    return filter_rows(docs, [text_col, lang_col], lambda: lambda texts, langs: [r[-1] for r in judge(texts, refs, rules, langs)])
