"""Text functions: words, sentences, normal forms, HTML."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

# fixed values: words that carry no entity
STOPWORDS = "a an and are as at be by for from has in is it its of on or that the this to was were which with".split()


def tokenise(text: Column) -> Column:
    """Lower-cased runs of letters and digits, in order; null gives none."""
    return F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit(r"([\p{L}\p{N}]+)"), F.lit(1))


def sentences(text: Column) -> Column:
    """Trimmed, non-empty stretches between sentence ends and line ends."""
    parts = F.transform(F.split(F.coalesce(text, F.lit("")), r"[.!?\n]+"), lambda s: F.trim(s))
    return F.filter(parts, lambda s: s != "")


def content_words(text: Column) -> Column:
    """Distinct words without stop words."""
    return F.array_except(F.array_distinct(tokenise(text)), F.array(*[F.lit(w) for w in STOPWORDS]))


def normalise(text: Column) -> Column:
    """Words without stop words, in order, joined by a space."""
    stop = F.array(*[F.lit(w) for w in STOPWORDS])
    return F.array_join(F.filter(tokenise(text), lambda w: ~F.array_contains(stop, w)), " ")


def tf_map(tokens: Column) -> Column:
    """Term frequencies as a map."""
    terms = F.array_distinct(tokens)
    return F.map_from_entries(
        F.transform(terms, lambda t: F.struct(t, F.size(F.filter(tokens, lambda x: x == t)).alias("n")))
    )


def html_text(html: Column) -> Column:
    """Visible text: scripts, styles, comments and tags go, common entities are decoded."""
    out = F.regexp_replace(html, r"(?is)<(script|style)[^>]*>.*?</\1>|<!--.*?-->", " ")
    out = F.regexp_replace(out, r"(?s)<[^>]*>", " ")
    for entity, char in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&")):
        out = F.replace(out, F.lit(entity), F.lit(char))
    return F.trim(F.regexp_replace(out, r"\s+", " "))
