"""Sentences, tokens, subword pieces."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

TOKEN = r"(\p{L}+|\d+|\S)"


def split_sentences(docs: DataFrame) -> DataFrame:
    """``doc_id, text`` -> ``doc_id, ord, sentence``: stretches up to an end mark or line end, without blank ones."""
    parts = F.split(F.regexp_replace("text", r"([.!?])\s+", "$1\n"), "\n")
    return docs.select("doc_id", F.posexplode(parts).alias("ord", "sentence")).filter(F.trim("sentence") != "")


def tokenize(sents: DataFrame, key: str = "sent_id", text: str = "sentence") -> DataFrame:
    """Words, numbers and single marks in order."""
    return sents.select(key, F.posexplode(F.regexp_extract_all(text, F.lit(TOKEN), F.lit(1))).alias("tok", "form"))


def blank_tokens(sents: DataFrame) -> DataFrame:
    """Tokens of sentences that are separated by blanks."""
    return sents.select("sent_id", F.posexplode(F.split("text", " ")).alias("tok", "form"))


def html_text(column) -> F.Column:
    """Text of a page: scripts, styles and tags go, five entities are decoded."""
    plain = F.regexp_replace(column, r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    plain = F.regexp_replace(plain, r"(?s)<[^>]*>", " ")
    for entity, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&")):
        plain = F.replace(plain, F.lit(entity), F.lit(char))
    return F.trim(F.regexp_replace(plain, r"\s+", " "))


def fit_pieces(tokens: DataFrame, size: int = 2000, longest: int = 6) -> list[str]:
    """A piece vocabulary: all single characters and the most frequent word parts. Returns at most ``size`` + characters."""
    starts = F.explode(F.sequence(F.lit(1), F.length("form")))
    words = tokens.groupBy("form").agg(F.count("*").alias("n"))
    parts = words.select("form", "n", starts.alias("a")).select("n", F.explode(F.transform(F.sequence(F.lit(1), F.lit(longest)), lambda k: F.substr("form", F.col("a"), k))).alias("piece"))
    counted = parts.groupBy("piece").agg(F.sum("n").alias("n"))
    top = counted.orderBy(F.desc("n"), "piece").limit(size)
    single = counted.filter(F.length("piece") == 1).select("piece")
    return sorted({r["piece"] for r in top.select("piece").union(single).collect()})


def wordpiece(tokens: DataFrame, pieces: list[str]) -> DataFrame:
    """``tokens`` with ``pieces``: greedily the longest piece first. Unknown characters are pieces of their own."""
    known, longest = frozenset(pieces), max(map(len, pieces), default=1)

    @F.pandas_udf("array<string>")
    def cut(forms: pd.Series) -> pd.Series:
        def one(w: str) -> list[str]:
            out, at = [], 0
            while at < len(w):
                k = next((k for k in range(min(longest, len(w) - at), 1, -1) if w[at : at + k] in known), 1)
                out.append(w[at : at + k])
                at += k
            return out

        uniques = {w: one(w) for w in forms.unique()}
        return forms.map(uniques)

    return tokens.withColumn("pieces", cut("form"))


def pool_pieces(piece_vectors: DataFrame, how: str = "first") -> DataFrame:
    """``sent_id, tok, piece, dim, value`` -> one vector a word: its first piece's, or the mean of all."""
    if how == "mean":
        return piece_vectors.groupBy("sent_id", "tok", "dim").agg(F.avg("value").alias("value"))
    return piece_vectors.groupBy("sent_id", "tok", "dim").agg(F.min_by("value", "piece").alias("value"))


def words_of_documents(docs: DataFrame) -> DataFrame:
    """``doc_id, pos, word``: lower-case letter runs in order."""
    return docs.select("doc_id", F.posexplode(F.regexp_extract_all(F.lower("text"), F.lit(r"(\p{L}+)"), F.lit(1))).alias("pos", "word"))
