"""A longest-suffix stemmer in the manner of Lovins (1968), applied to the vocabulary, never to tokens.

The longest listed ending is taken off if enough of the word is left; then the rest is recoded. This is a subset, not the
published stemmer: 84 of its 294 endings, each with a least length of the rest only; conditions on the last letters are absent.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StringType

#: Endings and the least length of the rest.
ENDINGS = {
    "alistically": 3, "arizability": 2, "izationally": 3, "antialness": 2, "arisations": 2, "entialness": 2, "allically": 4,
    "antaneous": 2, "antiality": 2, "arisation": 2, "ationally": 3, "ativeness": 2, "eableness": 5, "entations": 2, "entiality": 2, "entialize": 2,
    "ionalness": 2, "istically": 2, "izability": 2, "ableness": 2, "ariously": 2, "entation": 2, "ibleness": 2, "ionality": 2, "iousness": 2,
    "ization": 3, "ational": 3, "ability": 2, "aically": 2, "alities": 2, "arizing": 2, "ariness": 5, "atingly": 2, "atively": 2, "ativism": 2, "fulness": 2,
    "ingness": 2, "iveness": 2, "ousness": 2, "lessly": 2, "ancing": 3, "ations": 3, "ements": 2, "encies": 2, "ically": 3, "izable": 2, "nesses": 2,
    "able": 2, "ably": 2, "ages": 3, "ally": 3, "ance": 3, "ancy": 3, "ants": 3, "aric": 2, "ated": 3, "ates": 2, "atic": 3, "ator": 2, "ation": 3, "ness": 2,
    "ings": 4, "ions": 3, "ious": 2, "ised": 2, "ive": 2, "ized": 4, "less": 2, "ment": 3, "ous": 2, "ing": 3, "ion": 3, "ity": 2, "ed": 3, "en": 4, "er": 3, "es": 3, "ic": 3, "ly": 3, "al": 3, "or": 4, "s": 3, "e": 3, "y": 3,
}
#: Recoding of what is left.
RECODE = (("iev", "ief"), ("uct", "uc"), ("umpt", "um"), ("rpt", "rb"), ("metr", "meter"), ("olv", "olut"), ("bex", "bic"), ("ax", "ac"), ("ex", "ec"), ("ix", "ic"), ("lux", "luc"), ("uad", "uas"), ("vad", "vas"), ("cid", "cis"), ("lid", "lis"), ("erid", "eris"), ("pand", "pans"), ("ond", "ons"), ("lud", "lus"), ("rud", "rus"), ("mit", "mis"), ("ert", "ers"), ("yt", "ys"), ("yz", "ys"))
DOUBLED = "bdglmnprst"


def stem(word: str) -> str:
    for n in range(min(11, len(word) - 2), 0, -1):
        least = ENDINGS.get(word[-n:])
        if least is not None and len(word) - n >= least:
            word = word[:-n]
            break
    if len(word) > 1 and word[-1] == word[-2] and word[-1] in DOUBLED:
        word = word[:-1]
    for end, new in RECODE:
        if word.endswith(end):
            return word[: -len(end)] + new
    return word


@F.pandas_udf(StringType())
def stem_words(words: pd.Series) -> pd.Series:
    return words.map(stem, na_action="ignore")


def stemmed_vocabulary(vocab: DataFrame) -> DataFrame:
    """word, stem of each distinct word; counts of stems follow by joining and adding up."""
    return vocab.select("word", stem_words("word").alias("stem"))


def stemmed_counts(counts: DataFrame, vocab: DataFrame) -> DataFrame:
    """row_id, word (a stem), n from ``word_counts``."""
    return counts.join(stemmed_vocabulary(vocab), "word").groupBy("row_id", F.col("stem").alias("word")).agg(F.sum("n").alias("n"))
