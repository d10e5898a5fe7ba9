"""Any table as a corpus of (doc_id, domain, text, n_tokens)."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mixwright.functions.text import n_tokens


def adapt(df: DataFrame, id_col: str, domain: str, text: str | None = None, tokens: str | None = None, keep: tuple[str, ...] = ()) -> DataFrame:
    """Without a token column, tokens are the text's words."""
    if text is None and tokens is None:
        raise ValueError("either a text or a token column is needed")
    cols = [F.expr(id_col).alias("doc_id"), F.expr(domain).alias("domain")]
    if text is not None:
        cols.append(F.col(text).alias("text"))
    cols.append((F.expr(tokens).cast("long") if tokens else n_tokens(text)).alias("n_tokens"))
    return df.select(*cols, *keep)


def union_domains(parts: dict[str, DataFrame]) -> DataFrame:
    """Corpora under one another; ids get the part's name in front, so they stay apart."""
    named = [df.withColumn("doc_id", F.concat(F.lit(f"{name}:"), F.col("doc_id").cast("string"))) for name, df in parts.items()]
    return reduce(lambda a, b: a.unionByName(b, allowMissingColumns=True), named)


def html_text(pages: DataFrame, html: str = "html", out: str = "text") -> DataFrame:
    """Scripts, styles, comments and tags go, the five basic entities are read, white space is joined."""
    c = F.regexp_replace(F.coalesce(F.col(html), F.lit("")), r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    c = F.regexp_replace(F.regexp_replace(c, r"(?s)<!--.*?-->", " "), r"<[^>]*>", " ")
    for entity, char in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&amp;", "&")):
        c = F.replace(c, F.lit(entity), F.lit(char))
    return pages.withColumn(out, F.trim(F.regexp_replace(c, r"\s+", " ")))


def flatten_conversations(conv: DataFrame) -> DataFrame:
    """One text per conversation: turns in order, as ``role: text`` lines."""
    turns = F.array_sort(F.collect_list(F.struct("turn", "role", "text")))
    line = lambda t: F.concat(F.coalesce(t["role"], F.lit("")), F.lit(": "), F.coalesce(t["text"], F.lit("")))
    return conv.groupBy("conv_id").agg(turns.alias("turns")).select(
        "conv_id", F.size("turns").cast("long").alias("n_turns"), F.array_join(F.transform("turns", line), "\n").alias("text")
    )
