"""URL filter: rules on host and path first, boosted trees on lexical features for the rest.

The trees are fitted on URLs that rules have labelled. Beside lengths, counts and
entropy they see what is known of a URL's suffix (the host's last label) and of
its path's first segment: how many labelled URLs have it, and how many of those
are blocked. For the rows of the fit these statistics come from the other folds'
rows, and in some folds all rows of a suffix are as if its statistics weren't
known, so that the trees neither see a row's own label nor depend on a suffix
that a URL to be judged may not have.

Everything is DataFrame expressions and the JVM's own tree ensemble; no Python
runs on the executors.
"""

from __future__ import annotations

import string
from collections.abc import Sequence

from pyspark.ml.classification import GBTClassificationModel, GBTClassifier
from pyspark.ml.feature import VectorAssembler
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .stored import stored

#: verdict, host, path: fixed values of the filter's policy
RULES = (
    ("allow", "com", "/"),
    ("block", "example.com", "/en/"),
    ("allow", "www.example.com", "/en/"),
    ("block", "net", "/es/"),
    ("block", "net", "/fr/"),
)

#: what statistics of labels are kept of
STATISTICS = ("suffix", "segment")
FEATURES = ("length", "host_length", "path_length", "depth", "labels", "digits", "letters", "marks", "entropy", "params", "fragment", "secure", *(f"{s}_{x}" for s in STATISTICS for x in ("known", "rate")))

#: the ensemble and the statistics are fitted on this many labelled URLs at most, those of smallest hash
FIT_ROWS = 20_000
#: folds of the fit, and the last of them, in which a suffix counts as unknown
FOLDS, BLIND = 8, 2


def lower_ascii(c: Column) -> Column:
    return F.translate(c, string.ascii_uppercase, string.ascii_lowercase)


def parts(urls: DataFrame, url: str = "url") -> DataFrame:
    """Adds host, path and query; all empty where the URL is null or has no ``://``."""
    text = F.coalesce(F.col(url).cast("string"), F.lit(""))
    at = F.locate("://", text)
    rest = F.when(at > 0, F.substring(text, at + 3, F.length(text))).otherwise("")
    take = lambda pattern: F.regexp_extract(rest, pattern, 1)
    return urls.withColumns({"host": lower_ascii(take(r"\A([^/?#]*)")), "path": take(r"\A[^/?#]*([^?#]*)"), "query": take(r"\A[^?#]*\?([^#]*)")})


def rule_match(host: Column, path: Column, rules: Sequence[tuple[str, str, str]] = RULES) -> tuple[Column, Column]:
    """(rule, verdict) of the longest rule that fits, else nulls; ties go to the earlier."""
    name, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for v, h, p in sorted(rules, key=lambda r: len(r[1] + r[2])):  # the longest is tested first
        fits = ((host == h) | F.endswith(host, F.lit("." + h))) & F.startswith(path, F.lit(p))
        name, verdict = F.when(fits, h + p).otherwise(name), F.when(fits, v).otherwise(verdict)
    return name, verdict


def entropy(text: Column) -> Column:
    """Bits a character of the characters' own distribution; 0 for an empty text."""
    n = F.length(text).cast("double")
    share = lambda c: (n - F.length(F.replace(text, c))) / n
    return F.when(n == 0, 0.0).otherwise(F.aggregate(F.array_distinct(F.split(text, "")), F.lit(0.0), lambda a, c: a - F.when(c == "", 0.0).otherwise(share(c) * F.log2(share(c)))))


def count_of(text: Column, pattern: str) -> Column:
    return F.regexp_count(text, F.lit(pattern)).cast("double")


def features(split: DataFrame, url: str = "url") -> DataFrame:
    """Lexical features of rows with host, path and query; suffix is the host's last label, segment the path's first."""
    text = F.coalesce(F.col(url).cast("string"), F.lit(""))
    n = F.greatest(F.length(text), F.lit(1)).cast("double")
    return split.withColumns(
        {
            "suffix": F.substring_index("host", ".", -1),
            "segment": F.regexp_extract("path", r"\A/([^/]*)", 1),
            "length": F.length(text).cast("double"),
            "host_length": F.length("host").cast("double"),
            "path_length": F.length("path").cast("double"),
            "depth": count_of(F.col("path"), "/"),
            "labels": count_of(F.col("host"), r"\."),
            "digits": count_of(text, "[0-9]") / n,
            "letters": count_of(text, "[A-Za-z]") / n,
            "marks": count_of(text, "[-_%~+]") / n,
            "entropy": entropy(text),
            "params": F.when(F.col("query") == "", 0.0).otherwise(count_of(F.col("query"), "&") + 1),
            "fragment": F.contains(text, F.lit("#")).cast("double"),
            "secure": F.startswith(text, F.lit("https")).cast("double"),
        }
    )


def statistics(labelled: DataFrame, column: str, keys: list[str] | None = None, name: str | None = None) -> DataFrame:
    """(column, keys, name: struct(n, blocked)): labelled URLs with each value, and those of them that are blocked."""
    return labelled.groupBy(column, *(keys or [])).agg(F.struct(F.count(F.lit(1)).alias("n"), F.sum("label").alias("blocked")).alias(name or f"{column}_all"))


def as_features(column: str, n: Column, blocked: Column, prior: float = 0.5, weight: float = 2.0) -> dict[str, Column]:
    return {f"{column}_known": F.log1p(n.cast("double")), f"{column}_rate": (blocked + prior * weight) / (n + weight)}


def with_statistics(rows: DataFrame, tables: dict[str, DataFrame]) -> DataFrame:
    """Rows with the features of ``STATISTICS``; each table has at most ``FIT_ROWS`` rows, so it is broadcast."""
    zero = F.lit(0.0)
    for column, table in tables.items():
        known = F.col(f"{column}_all")
        rows = rows.join(F.broadcast(table), column, "left").withColumns(as_features(column, F.coalesce(known["n"], zero), F.coalesce(known["blocked"], zero))).drop(f"{column}_all")
    return rows


def out_of_fold(sample: DataFrame) -> DataFrame:
    """The fit's rows with statistics of the other folds; folds are of hosts, so that one site's URLs stay together."""
    rows = sample.withColumn("fold", F.pmod(F.xxhash64(F.lit("fold"), "host"), F.lit(FOLDS)).cast("int"))
    for column in STATISTICS:
        own, every = statistics(rows, column, ["fold"], "own"), statistics(rows, column)
        rows = rows.join(F.broadcast(every.join(own, column).select(column, "fold", (F.col(f"{column}_all.n") - F.col("own.n")).alias("n"), (F.col(f"{column}_all.blocked") - F.col("own.blocked")).alias("blocked"))), [column, "fold"])
        seen = (F.col("fold") < FOLDS - BLIND) if column == "suffix" else F.lit(True)
        rows = rows.withColumns(as_features(column, F.when(seen, F.col("n")).otherwise(0), F.when(seen, F.col("blocked")).otherwise(0.0))).drop("n", "blocked")
    return rows


def fit(labelled: DataFrame, fit_rows: int = FIT_ROWS, seed: int = 7) -> tuple[GBTClassificationModel, dict[str, DataFrame]] | None:
    """Trees and statistics from rows with features and ``label`` (1: block); None if a label is missing."""
    # rows that tie in hash and URL are the same in all that is used
    sample = stored(labelled.orderBy(F.xxhash64("url"), "url").limit(fit_rows))
    if len(sample.select("label").distinct().take(2)) < 2:
        return None
    vectors = VectorAssembler(inputCols=list(FEATURES), outputCol="features").transform(out_of_fold(sample)).select("features", "label").coalesce(1).cache()
    try:
        model = GBTClassifier(maxIter=12, maxDepth=4, maxBins=32, stepSize=0.2, seed=seed).fit(vectors)
    finally:
        vectors.unpersist()
    return model, {column: statistics(sample, column) for column in STATISTICS}


def scored(rows: DataFrame, fitted: tuple[GBTClassificationModel, dict[str, DataFrame]]) -> DataFrame:
    """Rows with features and the trees' ``score``, the probability of a block, and ``prediction``."""
    from pyspark.ml.functions import vector_to_array

    model, tables = fitted
    out = model.transform(VectorAssembler(inputCols=list(FEATURES), outputCol="features").transform(with_statistics(rows, tables)))
    return out.withColumn("score", vector_to_array("probability")[1])


def prepared(pages: DataFrame, id_col: str, url_col: str, rules: Sequence[tuple[str, str, str]]) -> DataFrame:
    """(page_id, url, host, path, features, rule, given, label) of every row; label is null where no rule fits."""
    split = features(parts(pages.select(F.col(id_col).alias("page_id"), F.col(url_col).cast("string").alias("url"))))
    name, verdict = rule_match(F.col("host"), F.col("path"), rules)
    return split.withColumns({"rule": name, "given": verdict}).withColumn("label", (F.col("given") == "block").cast("double"))


def held_out_accuracy(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", rules: Sequence[tuple[str, str, str]] = RULES, fit_rows: int = FIT_ROWS) -> DataFrame:
    """(label, n, right) of URLs that rules label, of every fifth host, by trees fitted on the other hosts' URLs."""
    labelled = prepared(pages, id_col, url_col, rules).where("given is not null")
    held = F.pmod(F.xxhash64(F.lit("held out"), "host"), F.lit(5)) == 0
    fitted = fit(labelled.where(~held), fit_rows)
    if fitted is None:
        raise ValueError("labels of one kind only")
    return scored(labelled.where(held), fitted).groupBy(F.col("given").alias("label")).agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("prediction") == F.col("label")).cast("long")).alias("right"))


def judge(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", rules: Sequence[tuple[str, str, str]] = RULES, fit_rows: int = FIT_ROWS) -> DataFrame:
    """Verdict on every URL: (page_id, host, path, rule, verdict, score).

    A rule's verdict stands. Where none fits, trees fitted on the URLs that
    rules have labelled say block or allow; ``score`` is their block
    probability. A null URL, or one without ``://``, has empty host and path and
    is judged by the trees. Without labels of both kinds the verdict is that of
    all labels, or allow. Repeated rows are judged each; other columns don't matter.
    """
    split = prepared(pages, id_col, url_col, rules)
    fitted = fit(split.where("given is not null"), fit_rows)
    if fitted is None:
        only = split.where("given is not null").select("given").take(1)
        rest, judged = F.lit(only[0][0] if only else "allow"), split.withColumn("score", F.lit(None).cast("double"))
    else:
        rest, judged = F.when(F.col("prediction") == 1, "block").otherwise("allow"), scored(split, fitted)
    return judged.select("page_id", "host", "path", "rule", F.coalesce("given", rest).alias("verdict"), F.when(F.col("given").isNull(), F.col("score")).alias("score"))
