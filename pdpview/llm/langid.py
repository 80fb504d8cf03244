"""Language identification by compression.

For each language a raw-content zstandard dictionary is filled with whole training texts. A text is compressed
with every dictionary; the language whose dictionary gives the smallest output wins. When the smallest and the
second smallest differ by less than ``margin`` of the smallest, the call is rejected (``narrow``).

The dictionaries are fitted on a bounded sample: in each language, one text per hash bucket of the id (``buckets`` of
them), of a longer text a stretch of ``max_chars`` characters from a place that its id picks, as many as fit
``dictionary_bytes``. Every language is learned; more than ``max_langs`` values of the column raise an error, as they
are no languages. Prediction reads whole texts.

Edge cases: null texts and texts without a letter give ``und`` with score 0; rows are independent; ties go to the
first language by name; without any training text every prediction is ``und``.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .texts import held_out, map_texts, new_key, per_worker


@dataclass(frozen=True)
class LangConfig:
    dictionary_bytes: int = 64 * 1024
    buckets: int = 64
    max_chars: int = 6000
    max_langs: int = 4096
    level: int = 9
    #: A text is compressed in parts of so many bytes, each with the dictionary anew: the text's own repeats matter less.
    part_bytes: int = 2048
    margin: float = 0.01


def sample(docs: DataFrame, cfg: LangConfig, id_col: str, text_col: str, lang_col: str) -> dict[str, list[str]]:
    """At most ``buckets`` training texts of each language."""
    d = docs.select(F.col(id_col).alias("i"), F.col(text_col).alias("t"), F.col(lang_col).alias("l"))
    d = d.filter(F.col("l").isNotNull() & ~held_out(F.col("i")) & (F.length("t") > 0))
    d = d.withColumn("h", F.xxhash64("i"))
    least = d.groupBy("l", F.pmod("h", F.lit(cfg.buckets)).alias("b")).agg(F.min("h").alias("h"))
    chosen = least.groupBy("l").agg(F.collect_list("h").alias("hs")).limit(cfg.max_langs + 1).collect()
    if len(chosen) > cfg.max_langs:
        raise ValueError(f"more than {cfg.max_langs} languages; raise max_langs or clean the column")
    wanted = [h for r in chosen for h in r.hs]  # at most max_langs * buckets numbers
    if not wanted:
        return {}
    ids = docs.sparkSession.createDataFrame([(r.l, h) for r in chosen for h in r.hs], "l string, h long")
    free = F.greatest(F.length("t") - cfg.max_chars + 1, F.lit(1))
    d = d.withColumn("t", F.substring("t", F.pmod(F.xxhash64("h"), free) + 1, F.lit(cfg.max_chars)))
    out: dict[str, dict[int, str]] = {}
    for r in d.join(F.broadcast(ids), ["l", "h"]).groupBy("l", "h").agg(F.min("t").alias("t")).collect():
        out.setdefault(r.l, {})[r.h] = r.t
    return {lang: [t for _, t in sorted(ts.items())] for lang, ts in sorted(out.items())}


def dictionaries(texts: dict[str, list[str]], cfg: LangConfig) -> dict[str, bytes]:
    out = {}
    for lang, ts in texts.items():
        raw = bytearray()
        for t in ts:
            if len(raw) >= cfg.dictionary_bytes:
                break
            raw += t.lower().encode("utf-8", "replace") + b"\n"
        out[lang] = bytes(raw[: cfg.dictionary_bytes])
    return {k: v for k, v in out.items() if len(v) >= 8}  # shorter content is no dictionary


class Identifier:
    def __init__(self, dicts: dict[str, bytes], cfg: LangConfig):
        import regex
        import zstandard as z

        self.cfg, self.letter = cfg, regex.compile(r"\p{L}").search
        self.langs = sorted(dicts)
        self.compress = []
        for lang in self.langs:
            d = z.ZstdCompressionDict(dicts[lang], dict_type=z.DICT_TYPE_RAWCONTENT)
            d.precompute_compress(level=cfg.level)
            self.compress.append(
                z.ZstdCompressor(level=cfg.level, dict_data=d, write_content_size=False, write_checksum=False, write_dict_id=False).compress
            )

    def sizes(self, text: str) -> list[int]:
        raw, n = text.lower().encode("utf-8", "replace"), self.cfg.part_bytes
        parts = [raw[i : i + n] for i in range(0, len(raw), n)]
        return [sum([len(c(p)) for p in parts]) for c in self.compress]

    def predict(self, text: str | None) -> tuple[str, float, bool]:
        """Language, score (relative margin mapped to 0..1) and whether the margin is too narrow to trust."""
        if not text or not self.langs or not self.letter(text):
            return "und", 0.0, True
        s = self.sizes(text)
        best = min(range(len(s)), key=lambda k: (s[k], k))
        rest = min((x for k, x in enumerate(s) if k != best), default=2 * s[best])
        gap = (rest - s[best]) / s[best]
        return self.langs[best], min(1.0, 0.5 + gap / 2), gap < self.cfg.margin


def fit(docs: DataFrame, cfg: LangConfig = LangConfig(), id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> dict[str, bytes]:
    return dictionaries(sample(docs, cfg, id_col, text_col, lang_col), cfg)


def identify(docs: DataFrame, dicts: dict[str, bytes], cfg: LangConfig = LangConfig(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, lang_pred, score, narrow. With ``narrow`` the general user treats the language as rejected."""
    shared, key = docs.sparkSession.sparkContext.broadcast(dicts), new_key()
    d = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"), held_out(F.col(id_col)).alias("held_out"))

    def make():
        predict = per_worker("langid", key, lambda: Identifier(shared.value, cfg)).predict
        return lambda ids, texts, out: [(i, h, *predict(t)) for i, t, h in zip(ids, texts, out, strict=True)]

    return map_texts(d, ["doc_id", "text", "held_out"], make, "doc_id long, held_out boolean, lang_pred string, score double, narrow boolean")
