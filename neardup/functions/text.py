"""Words, shingles and stems as column expressions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, StringType

from neardup.functions.hashing import XX, finished, premixed
from neardup.session import ship_package

SPLIT = r"[^\p{L}\p{N}]+"
#: Endings that the light stemmer takes off, the longest that fits, where three letters stay.
LIGHT_ENDINGS = ("ments", "ment", "tions", "tion", "heiten", "heit", "keiten", "keit", "ungen", "ung", "mente", "ciones", "ing", "ed", "es", "en", "er", "s", "e")


def words(text: str | Column) -> Column:
    """Lower-case runs of letters and digits, in order; null gives no words."""
    parts = F.split(F.lower(F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit(""))), SPLIT)
    return F.filter(parts, lambda x: x != "")


def light_stems(ws: Column) -> Column:
    return F.transform(ws, lambda w: F.regexp_replace(w, r"^(.{3,}?)(" + "|".join(LIGHT_ENDINGS) + ")$", "$1"))


def bound_once(value: Column, use) -> Column:
    """use(value) with value computed once for each row, however often use names it."""
    return F.element_at(F.transform(F.array(value), use), 1)


def word_ngrams(ws: Column, n: int = 8, short_doc: str = "whole", hashed: bool = False) -> Column:
    """The set of runs of n words.

    A text of 1 to n - 1 words is one gram ('whole'), none ('drop'), or is filled up with empty words
    ('pad'); without words there are no grams.
    """
    kind = "array<bigint>" if hashed else "array<string>"
    # Hashed grams are hashes of their words' hashes: each word is read once, however many grams it is in.
    made = (lambda run: F.xxhash64(run)) if hashed else (lambda run: F.array_join(run, " "))
    blank = F.xxhash64(F.lit("")) if hashed else F.lit("")

    def grams(w: Column) -> Column:
        runs = F.array_distinct(F.transform(F.sequence(F.lit(1), F.size(w) - (n - 1)), lambda i: made(F.slice(w, i, F.lit(n)))))
        whole = F.array(made(w))
        padded = F.array(made(F.concat(w, F.array_repeat(blank, F.lit(n) - F.size(w)))))
        short = {"whole": whole, "drop": F.array().cast(kind), "pad": padded}[short_doc]
        return F.when(F.size(w) >= n, runs).when(F.size(w) > 0, short).otherwise(F.array().cast(kind))

    return bound_once(F.transform(ws, lambda x: F.xxhash64(x)) if hashed else ws, grams)


def char_shingles(text: str | Column, n: int = 4) -> Column:
    """The set of substrings of n characters; spaces and punctuation count. Shorter texts are one shingle."""
    t = F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit(""))
    runs = F.array_distinct(F.transform(F.sequence(F.lit(1), F.length(t) - (n - 1)), lambda i: F.substring(t, i, F.lit(n))))
    return F.when(F.length(t) >= n, runs).when(F.length(t) > 0, F.array(t)).otherwise(F.array().cast("array<string>"))


def halves(text: str | Column) -> Column:
    """Hashes of the distinct words of a text's first and second half, as a struct (x, y); the first half of an odd number of words is the shorter one."""
    middle = lambda w: F.floor(F.size(w) / 2).cast("int")
    return bound_once(F.transform(words(text), lambda x: F.xxhash64(x)), lambda w: F.struct(F.array_distinct(F.slice(w, F.lit(1), middle(w))).alias("x"), F.array_distinct(F.slice(w, middle(w) + 1, F.size(w) - middle(w))).alias("y")))


def grams_of(df: DataFrame, cfg, hashed: bool = False, keep: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, grams, *keep) under a configuration."""
    if cfg.shingle == "char":
        g = char_shingles("text", cfg.n)
        return df.select("doc_id", (F.transform(g, lambda x: F.xxhash64(x)) if hashed else g).alias("grams"), *keep)
    if cfg.stem == "porter":
        stemmed = df.select("doc_id", words("text").alias("ws"), *keep).withColumn("ws", porter_stems("ws"))
        return stemmed.select("doc_id", word_ngrams(F.col("ws"), cfg.n, cfg.short_doc, hashed).alias("grams"), *keep)
    ws = words("text")
    return df.select("doc_id", word_ngrams(light_stems(ws) if cfg.stem == "light" else ws, cfg.n, cfg.short_doc, hashed).alias("grams"), *keep)


def _gram_sets(n: int, short_doc: str, blank: int):
    """(doc_id, grams) of rows (doc_id, hashes of words): the sets of word_ngrams(hashed=True), whose hash of a run folds the words' hashes one after the other."""

    def folded(mixed: np.ndarray, k: int) -> np.ndarray:
        """Hash of each run of k words."""
        many = len(mixed) - k + 1
        h = np.full(many, 42, np.uint64)
        for i in range(k):
            h = finished(h + XX[4] + np.uint64(8), mixed[i : i + many])
        return h.view(np.int64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            words = b.column(1)
            flat, size = words.flatten().to_numpy(zero_copy_only=False).view(np.uint64), words.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
            ends = np.cumsum(size)
            made = []
            for lo, hi in zip((ends - size).tolist(), ends.tolist(), strict=True):
                ws = flat[lo:hi]
                if hi - lo < n and hi > lo and short_doc == "pad":
                    ws = np.append(ws, np.full(n - (hi - lo), blank, np.int64).view(np.uint64))
                if len(ws) >= n:
                    made.append(np.unique(folded(premixed(ws), n)))
                else:
                    made.append(folded(premixed(ws), len(ws)) if len(ws) and short_doc == "whole" else np.zeros(0, np.int64))
            grams = pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, made)]).astype(np.int32)), pa.array(np.concatenate([np.zeros(0, np.int64), *made])))
            yield pa.RecordBatch.from_arrays([b.column(0), grams], ["doc_id", "grams"])

    return run


def gram_sets(df: DataFrame, cfg) -> DataFrame:
    """What grams_of(hashed=True) gives, with each set in order: words are hashed by Spark, and runs of them in Arrow batches at a small part of the cost."""
    if cfg.shingle == "char" or cfg.stem != "none":
        return grams_of(df, cfg, hashed=True)
    ship_package(df.sparkSession)
    blank = df.sparkSession.range(1).select(F.xxhash64(F.lit(""))).first()[0] if cfg.short_doc == "pad" else 0
    hashes = df.select("doc_id", F.transform(words("text"), lambda x: F.xxhash64(x)).alias("hashes"))
    return hashes.mapInArrow(_gram_sets(cfg.n, cfg.short_doc, blank), "doc_id bigint, grams array<bigint>")


def exploded(grams: DataFrame) -> DataFrame:
    """(doc_id, gram) rows."""
    return grams.select("doc_id", F.explode("grams").alias("gram"))


def gram_multiplicity(df: DataFrame, n: int = 8) -> DataFrame:
    """For each document all its grams and its distinct ones: the difference is what a set loses against a bag."""
    ws = df.select("doc_id", words("text").alias("ws"))
    sizes = ws.select("doc_id", F.greatest(F.size("ws") - (n - 1), F.least(F.size("ws"), F.lit(1))).cast("bigint").alias("n_grams"), F.size(word_ngrams(F.col("ws"), n)).cast("bigint").alias("n_distinct"))
    return sizes


# --- the stemmer of 1980, for English ---------------------------------------------------------------


def _measure(stem: str) -> int:
    """Number of times that a vowel run is followed by a consonant run."""
    kinds = "".join("c" if _consonant(stem, i) else "v" for i in range(len(stem)))
    return sum(a == "v" and b == "c" for a, b in zip(kinds, kinds[1:], strict=False))


def _consonant(w: str, i: int) -> bool:
    if w[i] in "aeiou":
        return False
    return w[i] != "y" or i == 0 or not _consonant(w, i - 1)


def _vowel(w: str) -> bool:
    return any(not _consonant(w, i) for i in range(len(w)))


def _double(w: str) -> bool:
    return len(w) > 1 and w[-1] == w[-2] and _consonant(w, len(w) - 1)


def _cvc(w: str) -> bool:
    return len(w) > 2 and _consonant(w, len(w) - 3) and not _consonant(w, len(w) - 2) and _consonant(w, len(w) - 1) and w[-1] not in "wxy"


#: Endings of steps 2, 3 and 4 with what takes their place.
STEP2 = (("ational", "ate"), ("tional", "tion"), ("enci", "ence"), ("anci", "ance"), ("izer", "ize"), ("abli", "able"), ("alli", "al"), ("entli", "ent"), ("eli", "e"), ("ousli", "ous"), ("ization", "ize"), ("ation", "ate"), ("ator", "ate"), ("alism", "al"), ("iveness", "ive"), ("fulness", "ful"), ("ousness", "ous"), ("aliti", "al"), ("iviti", "ive"), ("biliti", "ble"))
STEP3 = (("icate", "ic"), ("ative", ""), ("alize", "al"), ("iciti", "ic"), ("ical", "ic"), ("ful", ""), ("ness", ""))
STEP4 = ("al", "ance", "ence", "er", "ic", "able", "ible", "ant", "ement", "ment", "ent", "ion", "ou", "ism", "ate", "iti", "ous", "ive", "ize")


def porter(w: str) -> str:
    """Stem of a lower-case word."""
    if len(w) <= 2 or not w.isascii() or not w.isalpha():
        return w
    if w.endswith("sses") or w.endswith("ies"):
        w = w[:-2]
    elif w.endswith("s") and not w.endswith("ss"):
        w = w[:-1]
    if w.endswith("eed"):
        w = w[:-1] if _measure(w[:-3]) > 0 else w
    else:
        cut = next((w[: -len(e)] for e in ("ed", "ing") if w.endswith(e) and _vowel(w[: -len(e)])), None)
        if cut is not None:
            w = cut
            if w.endswith(("at", "bl", "iz")):
                w += "e"
            elif _double(w) and w[-1] not in "lsz":
                w = w[:-1]
            elif _measure(w) == 1 and _cvc(w):
                w += "e"
    if w.endswith("y") and _vowel(w[:-1]):
        w = w[:-1] + "i"
    for table in (STEP2, STEP3):
        hit = max((x for x in table if w.endswith(x[0])), key=lambda x: len(x[0]), default=None)
        if hit and _measure(w[: -len(hit[0])]) > 0:
            w = w[: -len(hit[0])] + hit[1]
    hit = max((e for e in STEP4 if w.endswith(e)), key=len, default=None)
    if hit and _measure(w[: -len(hit)]) > 1 and (hit != "ion" or w[: -len(hit)].endswith(("s", "t"))):
        w = w[: -len(hit)]
    if w.endswith("e") and (_measure(w[:-1]) > 1 or (_measure(w[:-1]) == 1 and not _cvc(w[:-1]))):
        w = w[:-1]
    if _measure(w) > 1 and _double(w) and w.endswith("l"):
        w = w[:-1]
    return w


@F.pandas_udf(ArrayType(StringType()))
def porter_stems(ws: Iterator[pd.Series]) -> Iterator[pd.Series]:
    """Stems of word lists, with a table of the words seen."""
    seen: dict[str, str] = {}
    for s in ws:
        out = []
        for row in s:
            for w in row:
                if w not in seen:
                    if len(seen) > 200_000:
                        seen.clear()
                    seen[w] = porter(w)
            out.append([seen.get(w) or porter(w) for w in row])
        yield pd.Series(out)
