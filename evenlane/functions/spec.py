"""Sort specifications: orderable key columns with direction and null placement, and exact comparisons with literals."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


@dataclass(frozen=True)
class Key:
    """One key: a SQL expression over the input, ascending or not, nulls first or last (Spark's default if None)."""

    expr: str
    asc: bool = True
    nulls_first: bool | None = None

    @property
    def first(self) -> bool:
        return self.asc if self.nulls_first is None else self.nulls_first


@dataclass(frozen=True)
class SortSpec:
    keys: tuple[Key, ...]

    @staticmethod
    def of(*keys: str | Key) -> SortSpec:
        return SortSpec(tuple(k if isinstance(k, Key) else Key(k) for k in keys))

    @property
    def names(self) -> list[str]:
        return [f"k{i}" for i in range(len(self.keys))]

    def add(self, df: DataFrame) -> DataFrame:
        """df with the key columns k0, k1, ... ; rejects types that have no order."""
        if not self.keys:
            raise ValueError("a sort needs at least one key")
        out = df.withColumns({n: F.expr(k.expr) for n, k in zip(self.names, self.keys, strict=True)})
        for n in self.names:
            if not orderable(out.schema[n].dataType):
                raise TypeError(f"{n}: {out.schema[n].dataType.simpleString()} has no order")
        return out

    def order(self, *more: str) -> list[Column]:
        """Sort columns, then the columns more, ascending."""
        out = []
        for n, k in zip(self.names, self.keys, strict=True):
            c = F.col(n)
            out.append((c.asc_nulls_first() if k.first else c.asc_nulls_last()) if k.asc else (c.desc_nulls_first() if k.first else c.desc_nulls_last()))
        return [*out, *[F.col(m).asc() for m in more]]

    def below_text(self, fence: dict, kinds: dict[str, T.DataType], tagged: bool = True) -> str | None:
        """below() of a record as SQL text, which is built in one call however long; None for key types without a plain literal."""
        names = [*self.names, *(["lane", "pos"] if tagged else [])]
        values = {n: literal(fence[n], kinds[n]) for n in names}
        if None in values.values():
            return None
        out = "false"
        for i, n in reversed(list(enumerate(names))):
            v, k = values[n], self.keys[i] if i < len(self.keys) else Key(n)
            if fence[n] is None:
                less = f"{n} is not null" if k.first else "false"
            else:
                less = f"coalesce({v} {'<' if k.asc else '>'} {n}, {'false' if k.first else 'true'})"
            out = f"({less} or ({v} <=> {n} and {out}))" if out != "false" else f"({less})"
        return out

    def prefix(self, n: int) -> SortSpec:
        """The first n keys."""
        return SortSpec(self.keys[:n])

    def sql_order(self) -> str:
        return ", ".join(f"{k.expr} {'ASC' if k.asc else 'DESC'} NULLS {'FIRST' if k.first else 'LAST'}" for k in self.keys)

    def _less(self, i: int, fence: Column, is_null: Column, row: Column) -> Column:
        """fence < row in the order of key i."""
        k = self.keys[i]
        beyond = (fence < row) if k.asc else (fence > row)
        return F.when(is_null, row.isNotNull() if k.first else F.lit(False)).otherwise(F.coalesce(beyond, F.lit(not k.first)))

    def below(self, fence: dict | Column, tagged: bool = True, row: Callable[[str], Column] = F.col, inclusive: bool = False) -> Column:
        """Whether a fence, a record or a struct column, lies strictly below (inclusive: or at) the row (k0.., lane, pos).

        Without tags the keys alone decide.
        """
        literal = isinstance(fence, dict)
        of = (lambda n: F.lit(fence[n])) if literal else (lambda n: fence[n])
        parts = [(self._less(i, of(n), F.lit(fence[n] is None) if literal else fence[n].isNull(), row(n)), of(n).eqNullSafe(row(n))) for i, n in enumerate(self.names)]
        if tagged:
            parts += [(of(n) < row(n), of(n) == row(n)) for n in ("lane", "pos")]
        out = F.lit(inclusive)
        for less, same in reversed(parts):
            out = less | (same & out)
        return out


def literal(value, kind: T.DataType) -> str | None:
    """SQL text of a value of a number, text or truth type; None for others."""
    name = kind.simpleString()
    if value is None:
        return f"cast(null as {name})"
    if isinstance(kind, (T.IntegralType, T.FractionalType)) and not isinstance(value, bool):
        return f"cast('{value!r}' as {name})" if isinstance(value, float) else f"cast('{value}' as {name})"
    if isinstance(kind, T.StringType) and name == "string":
        return f"cast(X'{value.encode().hex()}' as string)"
    return ("true" if value else "false") if isinstance(kind, T.BooleanType) else None


def orderable(t: T.DataType) -> bool:
    if isinstance(t, T.MapType) or t.typeName() == "variant":
        return False
    if isinstance(t, T.StructType):
        return all(orderable(f.dataType) for f in t.fields)
    return orderable(t.elementType) if isinstance(t, T.ArrayType) else True
