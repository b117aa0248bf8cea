"""Corpus selection and chunking."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vecrag.functions import vector as V


def select_corpus(docs: DataFrame, chosen: Column | DataFrame) -> DataFrame:
    """The documents that go into the index: by a predicate, or by a table of doc_id."""
    if isinstance(chosen, DataFrame):
        return docs.join(chosen.select("doc_id").distinct(), "doc_id", "left_semi")
    return docs.where(chosen)


def chunk(docs: DataFrame, size: int = 5, overlap: int = 0, ratio: float = 1.0) -> DataFrame:
    """(doc_id, chunk_no, offset, text, n_tokens): chunks of `size` sentences, shrunk by `ratio` (at least one sentence).

    offset is the chunk's first character within the document's joined sentences. A document without sentences has none.
    """
    per = max(1, round(size * ratio))
    step = per - overlap
    if step < 1:
        raise ValueError("a chunk must be longer than its overlap")
    sents = docs.select("doc_id", V.sentences("text").alias("sents")).where(F.size("sents") > 0)
    starts = F.sequence(F.lit(0), F.greatest(F.size("sents") - 1 - overlap, F.lit(0)), F.lit(step))
    rows = sents.select("doc_id", "sents", F.posexplode(starts).alias("chunk_no", "first"))
    before = F.aggregate(F.slice("sents", F.lit(1), F.col("first")), F.lit(0), lambda n, s: n + F.char_length(s) + 1)
    text = F.array_join(F.slice("sents", F.col("first") + 1, F.lit(per)), " ")
    return rows.select("doc_id", "chunk_no", before.cast("long").alias("offset"), text.alias("text"), V.token_count(text).alias("n_tokens"))


#: Elements whose content is not text of a page.
UNREAD = ("script", "style", "nav", "footer")


def strip_pages(pages: DataFrame) -> DataFrame:
    """(doc_id, text) of web pages: markup out, white space in one; a light source for retrieval tests."""
    body = F.col("html")
    for tag in UNREAD:
        body = F.regexp_replace(body, f"(?is)<{tag}[^>]*>.*?</{tag}>", " ")
    return pages.select(F.col("page_id").alias("doc_id"), F.trim(F.regexp_replace(F.regexp_replace(body, r"(?s)<[^>]*>", " "), r"\s+", " ")).alias("text"))
