"""How a table becomes a log."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.places import END, START


@dataclass(frozen=True)
class LogSpec:
    """Case columns, activity expression and a total order over a table.

    ``on_null``: ``drop`` events without an activity, ``error`` on them, or ``label:<X>`` to name them X.
    """

    name: str
    case_cols: tuple[str, ...]
    activity: str
    order_cols: tuple[str, ...]
    where: str | None = None
    case_where: str | None = None
    attrs: tuple[str, ...] = ()
    on_null: str = "drop"

    def events(self, df: DataFrame) -> DataFrame:
        """case_id, ord, activity, attrs of every event; only the columns named here are read."""
        rows = df.where(self.where) if self.where else df
        a: Column = F.expr(self.activity).cast("string")
        if self.on_null == "error":
            a = F.coalesce(a, F.raise_error(F.lit(f"null activity in log {self.name}")).cast("string"))
        elif self.on_null.startswith("label:"):
            a = F.coalesce(a, F.lit(self.on_null[6:]))
        a = F.when(a.isin(START, END), F.raise_error(F.lit(f"activity of log {self.name} equals a marker")).cast("string")).otherwise(a)
        attrs = F.create_map(*[x for c in self.attrs for x in (F.lit(c), F.col(c).cast("string"))]) if self.attrs else F.lit(None).cast("map<string,string>")
        out = rows.select(
            F.concat_ws("|", *[F.expr(c).cast("string") for c in self.case_cols]).alias("case_id"),
            F.struct(*[F.expr(c).alias(f"o{i}") for i, c in enumerate(self.order_cols)]).alias("ord"), a.alias("activity"), attrs.alias("attrs"),
        )
        out = out.where(self.case_where) if self.case_where else out
        return out.where("activity IS NOT NULL") if self.on_null == "drop" else out
