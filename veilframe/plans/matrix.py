"""The numeric matrix that a table is released as: attributes in order, a record key, a class left as it is."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.rng import key_text

KEY = "__key"


@dataclass(frozen=True)
class NumericMatrixSpec:
    value_cols: tuple[str, ...]
    key_cols: tuple[str, ...] = ()
    class_col: str | None = None
    passthrough: tuple[str, ...] = field(default=())

    @property
    def n(self) -> int:
        return len(self.value_cols)

    @property
    def kept(self) -> list[str]:
        """Columns that go along unperturbed."""
        return [*([self.class_col] if self.class_col else []), *self.passthrough]

    def only(self, columns: list[str]) -> NumericMatrixSpec:
        return replace(self, value_cols=tuple(columns))


def as_matrix(df: DataFrame, spec: NumericMatrixSpec, on_null: str = "error", repeated: str = "keep") -> DataFrame:
    """The attributes as doubles, the key as one text column, and what goes along.

    Nulls and NaN: "error" fails the job, "drop" drops the record, "mean" puts the attribute's mean.
    Records of one key: "keep" leaves them, which a release bears (they draw equal noise) but pairing by key does
    not; "number" numbers them inside their key, "error" fails the job. Either takes a shuffle by key.
    """
    missing = [c for c in (*spec.value_cols, *spec.key_cols, *spec.kept) if c not in df.columns]
    if missing:
        raise ValueError(f"no such columns: {missing}")
    values: dict[str, Column] = {c: F.when(F.isnan(F.col(c).cast("double")), None).otherwise(F.col(c).cast("double")) for c in spec.value_cols}
    if on_null == "error":
        values = {c: F.when(v.isNull(), F.raise_error(F.lit(f"null in attribute {c}")).cast("double")).otherwise(v) if df.schema[c].nullable else v for c, v in values.items()}
    out = df.select(key_text(spec.key_cols).alias(KEY), *(v.alias(c) for c, v in values.items()), *spec.kept)
    if on_null == "drop":
        out = out.dropna(subset=list(spec.value_cols))
    elif on_null == "mean":
        means = out.agg(*(F.avg(c).alias(c) for c in spec.value_cols)).first()
        out = out.fillna({c: means[c] for c in spec.value_cols if means[c] is not None})
    elif on_null != "error":
        raise ValueError(f"on_null is error, drop or mean, not {on_null}")
    if repeated == "keep":
        return out
    if repeated not in ("number", "error"):
        raise ValueError(f"repeated is keep, number or error, not {repeated}")
    number = F.row_number().over(Window.partitionBy(KEY).orderBy(*spec.value_cols))
    again = F.concat(F.col(KEY), F.lit("#"), number.cast("string")) if repeated == "number" else F.raise_error(F.concat(F.lit("a key repeats: "), F.col(KEY))).cast("string")
    return out.withColumn("__own", F.when(number == 1, F.col(KEY)).otherwise(again)).drop(KEY).withColumnRenamed("__own", KEY).select(*out.columns)


def with_homogeneous(df: DataFrame, name: str = "h") -> DataFrame:
    """The literal form with a coordinate that is always 1; the engine uses pairs of matrix and shift instead."""
    return df.withColumn(name, F.lit(1.0))
