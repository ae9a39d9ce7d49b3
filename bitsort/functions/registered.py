"""Arrow functions, table functions and their registration for SQL."""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from bitsort.operators.codecs import decode_marker, unpack_bits
from bitsort.operators.codes import unrank
from bitsort.operators.measure import MARKER

_VOWELS = "aeiou"


def _forms(word: str) -> str:
    """c for consonants, v for vowels; y after a consonant is a vowel."""
    out = ""
    for i, ch in enumerate(word):
        out += "v" if ch in _VOWELS or (ch == "y" and i > 0 and out[-1] == "c") else "c"
    return out


def _measure(word: str) -> int:
    """How many vowel-consonant turns a word has."""
    f = _forms(word)
    return sum(a == "v" and b == "c" for a, b in zip(f, f[1:], strict=False))


#: Suffix rules of the published stemmer, by step: (ending, replacement); fixed values.
STEP2 = (("ational", "ate"), ("tional", "tion"), ("enci", "ence"), ("anci", "ance"), ("izer", "ize"), ("abli", "able"), ("alli", "al"), ("entli", "ent"), ("eli", "e"), ("ousli", "ous"), ("ization", "ize"), ("ation", "ate"), ("ator", "ate"), ("alism", "al"), ("iveness", "ive"), ("fulness", "ful"), ("ousness", "ous"), ("aliti", "al"), ("iviti", "ive"), ("biliti", "ble"))
STEP3 = (("icate", "ic"), ("ative", ""), ("alize", "al"), ("iciti", "ic"), ("ical", "ic"), ("ful", ""), ("ness", ""))
STEP4 = ("al", "ance", "ence", "er", "ic", "able", "ible", "ant", "ement", "ment", "ent", "ion", "ou", "ism", "ate", "iti", "ous", "ive", "ize")


def _short_end(word: str) -> bool:
    return len(word) > 2 and _forms(word)[-3:] == "cvc" and word[-1] not in "wxy"


def stem(word: str) -> str:
    """The stem of an English word by suffix stripping in five steps."""
    if len(word) <= 2:
        return word
    if word.endswith("sses") or word.endswith("ies"):
        word = word[:-2]
    elif word.endswith("s") and not word.endswith("ss"):
        word = word[:-1]
    if word.endswith("eed"):
        word = word[:-1] if _measure(word[:-3]) > 0 else word
    else:
        for end in ("ed", "ing"):
            if word.endswith(end) and "v" in _forms(word[: -len(end)]):
                word = word[: -len(end)]
                if word.endswith(("at", "bl", "iz")):
                    word += "e"
                elif len(word) > 1 and word[-1] == word[-2] and _forms(word)[-1] == "c" and word[-1] not in "lsz":
                    word = word[:-1]
                elif _measure(word) == 1 and _short_end(word):
                    word += "e"
                break
    if word.endswith("y") and "v" in _forms(word[:-1]):
        word = word[:-1] + "i"
    for rules in (STEP2, STEP3):
        for end, new in sorted(rules, key=lambda r: -len(r[0])):
            if word.endswith(end):
                word = word[: -len(end)] + new if _measure(word[: -len(end)]) > 0 else word
                break
    for end in sorted(STEP4, key=lambda e: -len(e)):
        if word.endswith(end):
            base = word[: -len(end)]
            if _measure(base) > 1 and (end != "ion" or base[-1:] in ("s", "t")):
                word = base
            break
    if word.endswith("e"):
        base = word[:-1]
        if _measure(base) > 1 or (_measure(base) == 1 and not _short_end(base)):
            word = base
    if word.endswith("ll") and _measure(word) > 1:
        word = word[:-1]
    return word


@F.pandas_udf("string")
def stem_words(words: pd.Series) -> pd.Series:
    known = {w: stem(w) for w in words.dropna().unique()}
    return words.map(known)


@F.pandas_udf("array<long>")
def unrank_code(rank: pd.Series, n_bits: pd.Series, k: pd.Series, scheme: pd.Series) -> pd.Series:
    """Codes of ranks; rows are grouped by their parameters, not looped over."""
    out = pd.Series([None] * len(rank), dtype=object)
    for (n, j, s), at in pd.DataFrame({"n": n_bits, "k": k, "s": scheme}).groupby(["n", "k", "s"]).groups.items():
        for i, code in zip(at, unrank(rank[at].to_numpy(), int(n), int(j), s), strict=True):
            out[i] = code
    return out


@F.pandas_udf("array<long>")
def payload_rows(payload: pd.Series, rows: pd.Series) -> pd.Series:
    """Row numbers in a 32-bit marker-word payload."""
    codec = MARKER[32]
    return pd.Series([np.flatnonzero(unpack_bits(decode_marker(np.frombuffer(p, "<u4").astype(np.uint64), int(n), codec), 32, int(n))) for p, n in zip(payload, rows, strict=True)])


@F.udtf(returnType="w1: string, w2: string, w3: string, w4: string")
class FourTuples:
    """All ordered 4-combinations of the first ``cap`` words."""

    def eval(self, words: list, cap: int):
        yield from combinations((words or [])[:cap], 4)


@F.udtf(returnType="row_id: long")
class PayloadRows:
    """Row numbers in a payload, one row each."""

    def eval(self, payload: bytes, rows: int, base: int):
        bits = unpack_bits(decode_marker(np.frombuffer(payload, "<u4").astype(np.uint64), rows, MARKER[32]), 32, rows)
        for i in np.flatnonzero(bits):
            yield (int(i) + base,)


def register(spark: SparkSession) -> None:
    """stem_words, unrank_code, payload_rows, four_tuples and row_ids for spark.sql."""
    spark.udf.register("stem_words", stem_words)
    spark.udf.register("unrank_code", unrank_code)
    spark.udf.register("payload_rows", payload_rows)
    spark.udtf.register("four_tuples", FourTuples)
    spark.udtf.register("row_ids", PayloadRows)
