"""Deterministic random numbers of elements, and orders as numbers, as column expressions."""

from __future__ import annotations

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .md5 import bits52

SCALE = float(1 << 52)
#: salts of the three independent uses
VALUE, ROUTE, SHARD = "", "g", "s"


def element_key(*cols: Column | str) -> Column:
    """One string for a row of columns: lengths before values, and a mark for null, keep rows apart."""
    cols = [F.col(c) if isinstance(c, str) else c for c in cols]
    if len(cols) == 1:
        return cols[0].cast("string")
    one = lambda c: F.when(c.isNull(), "-").otherwise(F.concat(F.length(c.cast("string")).cast("string"), F.lit(":"), c.cast("string")))
    return F.concat_ws("", *(one(c) for c in cols))


def _portable(seed: int, salt: str, *cols: Column) -> Column:
    """52 bits of an md5, as a long."""
    text = F.concat_ws(":", F.lit(f"{salt}{seed}"), *(c.cast("string") for c in cols))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 13), 16, 10).cast("long")


def bits(kind: str, seed: int, salt: str, *cols: Column) -> Column:
    """52 random bits of some columns."""
    if kind == "portable":
        return _portable(seed, salt, *cols)
    return F.shiftrightunsigned(F.xxhash64(F.lit(f"{salt}{seed}"), *cols), 12)


def uniform(x: Column, j: Column, seed: int = 0, kind: str = "fast") -> Column:
    """A number in the open interval (0, 1) for element x and register j."""
    return (bits(kind, seed, VALUE, x, j) + 0.5) / SCALE


def route(x: Column, m: int, seed: int = 0, kind: str = "fast") -> Column:
    """The one register, 1..m, of element x."""
    return (bits(kind, seed, ROUTE, x) % m + 1).cast("int")


def shard(x: Column, shards: int, seed: int = 0, kind: str = "fast") -> Column:
    return (bits(kind, seed, SHARD, x) % shards).cast("int")


def tail(x: Column) -> Column:
    """What stands behind the salt and seed in the portable hash's text; nothing for null."""
    return F.concat_ws(":", F.lit(""), x.cast("string"))


def drawn(m: int, seed: int = 0):
    """A function of ``tail``: (j, bits), an element's portable ``route`` and its value's ``bits`` there, for whole columns at once."""

    @F.arrow_udf("struct<j:int,bits:long>")
    def draw(tails: pa.Array) -> pa.Array:
        coded = tails.dictionary_encode()
        names = coded.dictionary
        j = pa.array((bits52(names, f"{ROUTE}{seed}".encode(), [b""])[:, 0] % m + 1).astype("int32"))
        own = pc.binary_join_element_wise(names, j.cast(pa.string()).cast(names.type), ":")
        value = pa.array(bits52(own, f"{VALUE}{seed}".encode(), [b""])[:, 0])
        return pa.StructArray.from_arrays([j.take(coded.indices), value.take(coded.indices)], ["j", "bits"])

    # otherwise a filter on what it gives is moved before it, and all is drawn twice
    return draw.asNondeterministic()


def exponential(x: Column, w: Column, j: Column, seed: int = 0, kind: str = "fast") -> Column:
    """An exponential variable of rate w for element x and register j."""
    return -F.log(uniform(x, j, seed, kind)) / w


def linear(df: DataFrame, column: str) -> Column | None:
    """A column's values as numbers in the same order; None if they have no such form."""
    kind = df.schema[column].dataType
    if isinstance(kind, T.NumericType):
        return F.col(column).cast("double")
    if isinstance(kind, T.TimestampType):
        return F.unix_micros(column).cast("double")
    if isinstance(kind, T.TimestampNTZType):
        return F.timestamp_diff("MICROSECOND", F.lit("1970-01-01").cast("timestamp_ntz"), F.col(column)).cast("double")
    return F.unix_date(column).cast("double") if isinstance(kind, T.DateType) else None
