"""Sort keys: order columns with direction and null placement, made distinct by a record id."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


@dataclass(frozen=True)
class KeySpec:
    """``order``: column names, a leading ``-`` for descending. ``rid``: columns that make a record unique.

    Nulls come first ascending and last descending; NaN is greater than any number; both as in Spark's own sort.
    """

    order: tuple[str, ...]
    rid: tuple[str, ...]
    nulls_first: bool | None = None
    _types: dict = field(default_factory=dict, compare=False)

    @classmethod
    def of(cls, order: str | list[str], rid: str | list[str], nulls_first: bool | None = None) -> KeySpec:
        tup = lambda x: (x,) if isinstance(x, str) else tuple(x)
        return cls(tup(order), tup(rid), nulls_first)

    def validate(self, df: DataFrame) -> None:
        """Reject keys that Spark cannot order."""
        for name in [*(c.lstrip("-") for c in self.order), *self.rid]:
            kind = df.schema[name].dataType
            if isinstance(kind, (T.MapType, T.VariantType)):
                raise TypeError(f"{name}: {kind.simpleString()} has no order")

    def key(self, df: DataFrame) -> Column:
        """A struct that orders the records as asked, without ties and without null at its first field."""
        self.validate(df)
        fields: list[Column] = []
        for k, name in enumerate(self.order):
            down, name = name.startswith("-"), name.lstrip("-")
            first = not down if self.nulls_first is None else self.nulls_first
            fields.append(F.when(F.col(name).isNull(), F.lit(0 if first else 2)).otherwise(F.lit(1)).alias(f"n{k}"))
            fields += [c.alias(f"c{k}_{i}") for i, c in enumerate(_reversed(name, df.schema[name].dataType) if down else [F.col(name)])]
        fields += [F.col(c).alias(f"r{k}") for k, c in enumerate(self.rid)]
        return F.struct(*fields)

    def rid_text(self) -> Column:
        """The record id as text, for hashing."""
        return F.concat_ws(".", *(F.coalesce(F.col(c).cast("string"), F.lit("~")) for c in self.rid))


def _reversed(name: str, kind: T.DataType) -> list[Column]:
    """Columns whose ascending order is the descending order of ``name``."""
    c = F.col(name)
    if isinstance(kind, (T.FloatType, T.DoubleType)):
        return [F.when(F.isnan(c), 0).otherwise(1), -c]
    if isinstance(kind, (T.ByteType, T.ShortType, T.IntegerType, T.LongType)):
        return [-c.cast("decimal(20,0)")]
    if isinstance(kind, T.DecimalType):
        return [-c]
    if isinstance(kind, T.DateType):
        return [-F.unix_date(c)]
    if isinstance(kind, (T.TimestampType, T.TimestampNTZType)):
        return [-F.unix_micros(c.cast("timestamp"))]
    if isinstance(kind, T.BooleanType):
        return [~c]
    if isinstance(kind, (T.StringType, T.BinaryType)):
        # complemented bytes, then a mark above all of them, so that a prefix comes after what it begins
        return [F.concat(F.translate(F.hex(c), "0123456789ABCDEF", "FEDCBA9876543210"), F.lit("G"))]
    raise TypeError(f"{name}: descending order of {kind.simpleString()} is not supported")
