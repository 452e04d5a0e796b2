"""Python table functions."""

from __future__ import annotations

import re

from pyspark.sql.functions import AnalyzeArgument, AnalyzeResult, udtf
from pyspark.sql.types import IntegerType, StringType, StructType


@udtf
class WordShingles:
    """word_shingles(text, n): the distinct runs of n words, or all words of a shorter text."""

    @staticmethod
    def analyze(text: AnalyzeArgument, n: AnalyzeArgument) -> AnalyzeResult:
        return AnalyzeResult(StructType().add("shingle", StringType()))

    def eval(self, text: str, n: int):
        # Letters and digits of any script: everything that isn't a word character, and the underscore, splits.
        words = [w for w in re.split(r"[\W_]+", (text or "").lower()) if w]
        if words:
            for g in dict.fromkeys(" ".join(words[i : i + n]) for i in range(max(1, len(words) - n + 1))):
                yield (g,)


@udtf
class BandRows:
    """band_rows(sig, r): each band's number and first value; the values' type is that of the signature."""

    @staticmethod
    def analyze(sig: AnalyzeArgument, r: AnalyzeArgument) -> AnalyzeResult:
        return AnalyzeResult(StructType().add("band_id", IntegerType()).add("first", sig.dataType.elementType))

    def eval(self, sig: list, r: int):
        for i in range(len(sig) // r):
            yield i, sig[i * r]
