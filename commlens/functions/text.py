"""Preprocessing of short texts, as column expressions: words and hashtags, without stop words, stemmed, of the kinds that carry a topic.

Stems and kinds come from endings alone (no tagger is trained here): words that end like adverbs or adjectives are left out, what is left counts as noun or
verb; hashtags stay as they are."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Common function words of English.
STOP_WORDS = (
    "a about after all also an and any are as at be because been but by can could did do does for from had has have he her him his how i if in into is it its just like"
    " me more most my no not of on one only or other our out over she so some such than that the their them then there these they this to up us was we were what when"
    " which who will with would you your"
).split()
WORD = r"#?[\p{L}\p{N}_]+"
#: Endings of adverbs and adjectives of five letters or more.
OTHER_KINDS = r"^[\p{L}]{2,}(?:ly|ous|ful|less|able|ible|ive|ish)$"
#: Endings taken off, in order, each once: plural and third person, participles, and a doubled last consonant.
ENDINGS = ((r"^(.{2,})ies$", r"$1y"), (r"^(.{3,}[^su])s$", r"$1"), (r"^(.{3,})ing$", r"$1"), (r"^(.{3,})ed$", r"$1"), (r"^(.{2,})(bb|dd|gg|mm|nn|pp|rr|tt)$", r"$1$2"))


def stem(word: Column) -> Column:
    for pattern, by in ENDINGS[:-1]:
        word = F.regexp_replace(word, pattern, by)
    return F.when(word.rlike(ENDINGS[-1][0]), F.substring(word, 1, F.length(word) - 1)).otherwise(word)


def terms(text: Column) -> Column:
    """The terms of a text as an array, repeats included; null text has none."""
    words = F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit(WORD), F.lit(0))
    kept = F.filter(words, lambda w: w.startswith("#") | ~(w.isin(*STOP_WORDS) | w.rlike(OTHER_KINDS) | w.rlike(r"^[\p{N}_]+$")))
    return F.transform(kept, lambda w: F.when(w.startswith("#"), w).otherwise(stem(w)))


def preprocessed(docs: DataFrame, min_words: int = 2) -> DataFrame:
    """(doc_id, user_id, words) from (doc_id, user_id, text): documents of at least that many terms; users without a document go with their documents."""
    return docs.select("doc_id", "user_id", terms(F.col("text")).alias("words")).where(F.size("words") >= min_words)
