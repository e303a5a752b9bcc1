"""Rows of any type as texts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


def text_of(df: DataFrame, name: str) -> Column:
    kind, c = df.schema[name].dataType, F.col(f"`{name}`")
    if isinstance(kind, (T.StructType, T.ArrayType, T.MapType, T.VariantType)):
        return F.to_json(c)
    if isinstance(kind, T.BinaryType):
        return F.base64(c)
    if isinstance(kind, T.TimestampType):
        return F.date_format(F.to_utc_timestamp(c, F.current_timezone()), "yyyy-MM-dd'T'HH:mm:ss")
    return c.cast("string")


def render_rows(df: DataFrame, id_col: str, columns: list[str] | None = None, template: str | None = None, key: Column | None = None, null_policy: str = "empty") -> DataFrame:
    """(row_id, text, key): ``template`` names columns in braces; else name=value pairs."""
    names = columns or [c for c in df.columns if c != id_col]
    parts = {n: F.coalesce(text_of(df, n), F.lit("")) for n in names}
    if template is None:
        text = F.concat_ws(", ", *[F.concat(F.lit(f"{n}="), p) for n, p in parts.items()])
    else:
        pieces: list[Column] = []
        rest = template
        while "{" in rest:
            plain, _, rest = rest.partition("{")
            name, _, rest = rest.partition("}")
            pieces += [F.lit(plain), F.coalesce(text_of(df, name), F.lit(""))]
        text = F.concat(*pieces, F.lit(rest))
    if null_policy == "drop":
        df = df.where(" AND ".join(f"`{n}` IS NOT NULL" for n in names))
    elif null_policy != "empty":
        raise ValueError(f"unknown null policy {null_policy!r}")
    return df.select(F.col(id_col).cast("long").alias("row_id"), text.alias("text"), (key if key is not None else F.lit(None).cast("string")).alias("key"))


def texts(df: DataFrame, id_col: str, text_col: str = "text", key: Column | None = None) -> DataFrame:
    """(row_id, text, key) of a table that has texts already."""
    return df.select(F.col(id_col).cast("long").alias("row_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"), (key if key is not None else F.lit(None).cast("string")).alias("key"))
