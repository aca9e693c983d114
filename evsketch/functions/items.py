"""Items: one canonical value for a column or a tuple of columns."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


def _text(c: Column, kind: T.DataType) -> Column:
    """A text that equal values share and different values don't; null where ``c`` is."""
    if isinstance(kind, T.StringType):
        return c
    if isinstance(kind, (T.ByteType, T.ShortType, T.IntegerType, T.LongType)):
        return c.cast("long").cast("string")
    if isinstance(kind, (T.FloatType, T.DoubleType)):
        d = c.cast("double")
        return F.when(d == 0, F.lit("0.0")).otherwise(d.cast("string"))  # both zeros are one item
    if isinstance(kind, T.DecimalType):
        return c.cast(T.DecimalType(38, min(18, max(kind.scale, 6)))).cast("string")
    if isinstance(kind, T.DateType):
        return F.unix_date(c).cast("string")
    if isinstance(kind, T.TimestampType):
        return F.unix_micros(c).cast("string")
    if isinstance(kind, T.TimestampNTZType):
        return F.date_format(c, "yyyy-MM-dd'T'HH:mm:ss.SSSSSS")
    if isinstance(kind, T.BooleanType):
        return c.cast("string")
    if isinstance(kind, T.BinaryType):
        return F.hex(c)
    if isinstance(kind, T.ArrayType):
        inner = F.transform(c, lambda x: _framed(_text(x, kind.elementType)))
        return F.concat(F.lit("["), F.array_join(inner, ""), F.lit("]"))
    if isinstance(kind, T.StructType):
        parts = [_framed(_text(c[f.name], f.dataType)) for f in kind.fields]
        return F.when(c.isNotNull(), F.concat(F.lit("("), *parts, F.lit(")")))
    if isinstance(kind, T.MapType):
        entries = T.StructType([T.StructField("key", kind.keyType), T.StructField("value", kind.valueType)])
        return _text(F.array_sort(F.map_entries(c)), T.ArrayType(entries))
    raise TypeError(f"{kind.simpleString()} can't be an item")


def _framed(text: Column) -> Column:
    """Length-prefixed, so that neighbours never run together; null is marked."""
    return F.coalesce(F.concat(F.length(text).cast("string"), F.lit(":"), text), F.lit("~"))


def canonical_item(df: DataFrame, cols: str | Sequence[str]) -> Column:
    """The item of each row as text, null if any of its columns is null (such a row is no item).

    One column gives its plain text; several are joined by ``|`` after their lengths are framed.
    """
    cols = [cols] if isinstance(cols, str) else list(cols)
    texts = [_text(F.col(c), df.schema[c].dataType) for c in cols]
    if len(texts) == 1:
        return texts[0]
    joined = F.concat(*[_framed(t) for t in texts])
    missing = F.lit(False)
    for t in texts:
        missing = missing | t.isNull()
    return F.when(~missing, joined)
