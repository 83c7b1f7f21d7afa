"""Benchmark passages in a corpus, by a prefix-filtered join; DataFrame functions only.

A window is ``n`` consecutive words of a benchmark item, or the whole of a
shorter one. Its words are ordered by how rare they are in the corpus; to
contain the window a text must have the rarest of them, so one word of each
window, its *prefix*, is all that is joined. A meeting gives the only place
where the window could lie; places before the text's start or past its end go,
and what is left is compared word by word.
"""

from __future__ import annotations

import string

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .stored import stored
from .windows import NULL_ID, free_names

#: bytes of a benchmark's distinct words up to which they are broadcast; above, the join shuffles
BROADCAST_BYTES = 32 << 20

_NOT_WORD = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def lowered(text: Column) -> Column:
    """A-Z in lower case, all else as it is."""
    plain = F.octet_length(text) == F.length(text)
    return F.when(plain, F.lower(text)).otherwise(F.translate(text, string.ascii_uppercase, string.ascii_lowercase))


def words(text: Column) -> Column:
    """Runs of digits, letters and code points from 0x80, in lower case; null has none."""
    return F.array_remove(F.split(lowered(F.coalesce(text.cast("string"), F.lit(""))), _NOT_WORD), "")


def item_windows(benchmark: DataFrame, n: int, id_col: str = "item_id", text_col: str = "text") -> DataFrame:
    """(window, len, items): each different window of all items, its words joined by a space."""
    w = benchmark.select(F.col(id_col).cast("string").alias("item"), words(F.col(text_col)).alias("w")).where("size(w) > 0")
    starts = F.sequence(F.lit(1), F.greatest(F.size("w") - (n - 1), F.lit(1)))
    each = w.select("item", F.explode(F.transform(starts, lambda i: F.array_join(F.slice("w", i, n), " "))).alias("window"))
    return each.groupBy("window").agg(F.collect_set("item").alias("items")).withColumn("len", F.size(F.split("window", " ")))


def sized(df: DataFrame, column: str) -> DataFrame:
    """``df`` with a broadcast hint if ``column``'s bytes are within the bound."""
    size = df.agg(F.sum(F.octet_length(column) + 32)).first()[0] or 0
    return F.broadcast(df) if size <= BROADCAST_BYTES else df


def hits(texts: DataFrame, benchmark: DataFrame, n: int = 13, id_col: str = "item_id", text_col: str = "text") -> DataFrame:
    """(doc, tag, found): the verified occurrences of each text that has any.

    ``texts`` has doc, tag and text; ``found`` is an array of (start, len,
    items), words counted from 0.
    """
    windows = stored(item_windows(benchmark, n, id_col, text_col))
    vocabulary = windows.select(F.explode(F.split("window", " ")).alias("word")).distinct()
    said = texts.select(F.explode(words(F.col("text"))).alias("word"))
    count = said.join(sized(vocabulary, "word"), "word", "left_semi").groupBy("word").agg(F.count(F.lit(1)).alias("n"))
    # a window with a word that no text has cannot occur
    places = windows.select("window", F.posexplode(F.split("window", " ")).alias("offset", "word"))
    ranked = places.join(count, "word", "left").withColumn("rank", F.row_number().over(Window.partitionBy("window").orderBy(F.col("n").asc_nulls_first(), "word", "offset")))
    prefix = ranked.where("rank = 1 and n is not null").select("window", "word", "offset")
    prefix = stored(prefix.join(windows, "window"))
    rarest = prefix.select("word").distinct()
    at = texts.select("doc", "tag", F.posexplode(words(F.col("text"))).alias("at", "word"))
    met = at.join(sized(rarest, "word"), "word", "left_semi").join(prefix, "word").withColumn("start", F.col("at") - F.col("offset")).where("start >= 0")
    return met.groupBy("doc", "tag").agg(F.collect_list(F.struct("start", "len", "window", "items")).alias("met"))


def decontaminate(docs: DataFrame, benchmark: DataFrame, n: int = 13, share: int = 20, id_col: str = "doc_id", text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Benchmark words in every row of ``docs``.

    Gives doc_id, n_words, n_hit (words inside an occurrence of a window),
    n_items, items_sha256 (their ids as strings, sorted, comma-joined) and
    contaminated (``n_hit > 0 and share * n_hit >= n_words``), and the columns of
    ``keep``. Null texts have no words; null item ids are not counted as items;
    items without words have no windows; repeated rows are judged each.
    """
    row = ["doc_id", *(keep or [])]
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    key = {"doc": F.coalesce(F.col(id_col).cast("long"), F.lit(NULL_ID)), "tag": F.hash(text)}
    texts = docs.select(*(c.alias(k) for k, c in key.items()), text.alias("text"))
    found = hits(texts, benchmark, n).withColumnsRenamed({"doc": "_doc", "tag": "_tag", "met": "_met"})
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), *(F.col(c).alias(c) for c in keep or []), text.alias("_text"), *(c.alias(f"_k{k}") for k, c in key.items()))
    joined = rows.join(found, (F.col("_kdoc") == F.col("_doc")) & (F.col("_ktag") == F.col("_tag")), "left").withColumn("_w", words(F.col("_text")))
    true = F.filter("_met", lambda m: (m["start"] + m["len"] <= F.size("_w")) & (F.array_join(F.slice("_w", m["start"] + 1, m["len"]), " ") == m["window"]))
    judged = joined.withColumn("_true", F.when(F.col("_met").isNotNull(), true))
    inside = F.array_distinct(F.flatten(F.transform("_true", lambda m: F.sequence(m["start"], m["start"] + m["len"] - 1))))
    items = F.array_sort(F.array_distinct(F.flatten(F.transform("_true", lambda m: m["items"]))))
    none = F.lit(None).cast("array<string>")
    result = judged.select(*row, F.size("_w").cast("long").alias("n_words"), F.coalesce(F.when(F.size("_true") > 0, F.size(inside)), F.lit(0)).cast("long").alias("n_hit"), F.coalesce(F.when(F.size("_true") > 0, items), none, F.array().cast("array<string>")).alias("_items"))
    return result.select(
        *row, "n_words", "n_hit", F.size("_items").cast("long").alias("n_items"), F.sha2(F.array_join("_items", ",").cast("binary"), 256).alias("items_sha256"),
        ((F.col("n_hit") > 0) & (share * F.col("n_hit") >= F.col("n_words"))).alias("contaminated"),
    )


def clean(docs: DataFrame, benchmark: DataFrame, n: int = 13, share: int = 20) -> DataFrame:
    """Rows of ``docs``, all columns, that are not contaminated.

    Null and empty texts have no words and stay; repeated rows stay or go
    together; without items all rows stay; an empty table stays empty.
    """
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    id_, hash_ = free_names(docs, "id", "hash")
    key = {id_: F.coalesce(F.col("doc_id").cast("long"), F.lit(NULL_ID)), hash_: F.hash(text)}
    # stored, or a filter on the verdict would work out the words anew for each use
    keyed = docs.select("doc_id", "text", *(c.alias(k) for k, c in key.items()))
    judged = stored(decontaminate(keyed, benchmark, n, share, keep=list(key)).select(*key, "contaminated"))
    return docs.withColumns(key).join(judged.where("contaminated").select(*key).distinct(), list(key), "left_anti").select(*docs.columns)
