"""Sentence units and their symbols."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

DELIMITERS = "[.!?\\n]+"
#: One word of the original spacing, or one other mark.
GOLD_TOKEN = "[\\p{L}\\p{N}]+|[^\\s\\p{L}\\p{N}]"


def sentences(docs: DataFrame, *, id_col: str = "doc_id", text: str = "text", keep: tuple[str, ...] = ("lang", "source"), delim: str = DELIMITERS, lower: bool = True) -> DataFrame:
    """``sent_id, doc_id, sent_no, <keep>, raw, s, n``: units between marks that
    end a sentence; ``s`` is the unit without white space.  Empty units go, and
    keep their number.  Null texts have no units."""
    body = F.lower(text) if lower else F.col(text)
    units = docs.select(F.col(id_col).alias("doc_id"), *keep, F.posexplode(F.split(body, delim)).alias("sent_no", "raw"))
    s = F.regexp_replace("raw", "\\s+", "")
    return units.withColumn("s", s).where("s <> ''").select(
        F.concat_ws(":", F.col("doc_id").cast("string"), F.col("sent_no").cast("string")).alias("sent_id"), "doc_id", "sent_no", *keep, "raw", "s", F.length("s").alias("n"))


def symbols(s: Column) -> Column:
    """Code points as an array of strings."""
    return F.filter(F.split(s, ""), lambda c: c != "")


def is_usable(symbol: Column, script: str = "letter") -> Column:
    """Whether a symbol belongs to the target script."""
    return symbol.rlike("^\\p{IsHan}$" if script == "han" else "^\\p{L}$")


def gold_words(raw: Column) -> Column:
    return F.regexp_extract_all(raw, F.lit(GOLD_TOKEN), F.lit(0))


def spans(words: Column) -> Column:
    """``start * 2^20 + end`` of each word, in order."""
    ends = F.aggregate(words, F.array(F.lit(0).cast("long")), lambda acc, w: F.concat(acc, F.array(F.element_at(acc, -1) + F.length(w))))
    # two shifted copies, so that the running sum is not evaluated again for each word
    return F.zip_with(F.slice(ends, 1, F.size(words)), F.slice(ends, 2, F.size(words)), lambda a, b: a * 1048576 + b)
