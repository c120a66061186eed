"""Records of any format as one tagged sequence, compiled from their schema.

A flat record becomes, attribute by attribute, column tag, name, value tag, value. A
nested record repeats this at every level, as the value of its parent. A list is one
value: its elements joined. Text is left as it is. The compiler walks the schema on the
driver and returns one Column; no row-wise code is involved.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F, types as T

# The tags of the sequence format.
COL, VAL, CLS, SEP, MASK = "[COL]", "[VAL]", "[CLS]", "[SEP]", "[MASK]"


def escape(text: Column) -> Column:
    """A tag inside a value or name gets a backslash; white space becomes single spaces."""
    tags = r"\[(COL|VAL|CLS|SEP|MASK)\]"
    return F.trim(F.regexp_replace(F.regexp_replace(text, tags, r"\\[$1\\]"), r"\s+", " "))


def render(value: Column, dtype: T.DataType) -> Column:
    """A primitive as text: money with two digits, dates by day, booleans in lower case."""
    if isinstance(dtype, (T.DoubleType, T.FloatType)):
        value = value.cast("decimal(18,2)")
    if isinstance(dtype, (T.TimestampType, T.TimestampNTZType)):
        return F.date_format(value, "yyyy-MM-dd")
    if isinstance(dtype, T.BooleanType):
        return F.when(value, "true").when(~value, "false")
    return escape(value.cast("string")) if isinstance(dtype, T.StringType) else value.cast("string")


def _leaves(value: Column, dtype: T.DataType, tagged: bool) -> Column:
    """One string for an element of a list."""
    if isinstance(dtype, T.StructType):
        if tagged:
            return compile_struct(value, dtype, "skip", "tagged")
        return F.concat_ws(" ", *[_leaves(value[f.name], f.dataType, tagged) for f in dtype.fields])
    if isinstance(dtype, T.ArrayType):
        return F.array_join(F.transform(value, lambda x: _leaves(x, dtype.elementType, tagged)), " ")
    if isinstance(dtype, T.MapType):
        entries = F.array_sort(F.map_entries(value))
        return F.array_join(F.transform(entries, lambda e: F.concat_ws(" ", e["key"].cast("string"), _leaves(e["value"], dtype.valueType, tagged))), " ")
    return render(value, dtype)


def _value(value: Column, dtype: T.DataType, nulls: str, lists: str) -> Column:
    if isinstance(dtype, T.StructType):
        return compile_struct(value, dtype, nulls, lists)
    if isinstance(dtype, T.MapType):
        entries = F.array_sort(F.map_entries(value))
        each = lambda e: F.concat_ws(" ", F.lit(COL), escape(e["key"].cast("string")), F.lit(VAL), _value(e["value"], dtype.valueType, nulls, lists))
        return F.array_join(F.transform(entries, each), " ")
    return _leaves(value, dtype, lists == "tagged")


def compile_struct(rec: Column, schema: T.StructType, nulls: str = "skip", lists: str = "values") -> Column:
    """nulls: "empty" keeps the name with no value, "skip" leaves the attribute out. lists: "values" or "tagged" objects."""
    parts = []
    for f in schema.fields:
        value = _value(rec[f.name], f.dataType, nulls, lists)
        head = F.concat_ws(" ", F.lit(COL), escape(F.lit(f.name)), F.lit(VAL))
        if nulls == "skip":
            parts.append(F.when(rec[f.name].isNotNull(), F.concat_ws(" ", head, value)))
        else:
            parts.append(F.concat_ws(" ", head, F.coalesce(value, F.lit(""))))
    return F.concat_ws(" ", *parts) if parts else F.lit("")


def serialize(df: DataFrame, rec: str, fmt: str, out: str = "seq", nulls: str | None = None, lists: str = "values") -> DataFrame:
    """fmt: "rel" (empty values kept), "semi" (missing attributes left out) or "text"."""
    if fmt == "text":
        return df.withColumn(out, F.col(rec).cast("string"))
    schema = df.schema[rec].dataType
    return df.withColumn(out, compile_struct(F.col(rec), schema, nulls or {"rel": "empty", "semi": "skip"}[fmt], lists))


def encode_pair(left: Column, right: Column) -> Column:
    """Input of sequence-pair classification: start, left, separator, right, separator."""
    return F.concat_ws(" ", F.lit(CLS), left, F.lit(SEP), right, F.lit(SEP))


def truncate_pair(left: Column, right: Column, budget: int) -> tuple[Column, Column]:
    """Longest first: the shorter side keeps all it has up to half, the longer gets the rest."""
    a, b = F.split(left, " "), F.split(right, " ")
    na, nb = F.size(a), F.size(b)
    half = budget // 2
    keep_a = F.least(na, F.greatest(F.lit(half), F.lit(budget) - nb))
    keep_b = F.least(nb, F.lit(budget) - keep_a)
    return F.array_join(F.slice(a, F.lit(1), keep_a), " "), F.array_join(F.slice(b, F.lit(1), keep_b), " ")


def parse_records(df: DataFrame, col: str, schema: str | None = None, out: str = "rec") -> DataFrame:
    """JSON text as records: by schema, or as an open map of the top level's values."""
    return df.withColumn(out, F.from_json(F.col(col), schema or "map<string,string>"))
