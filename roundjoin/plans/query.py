"""Full natural equijoins over named attributes."""

from __future__ import annotations

import re
from collections import Counter
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

_NUMERIC = (T.ByteType, T.ShortType, T.IntegerType, T.LongType)


@dataclass(frozen=True)
class Atom:
    """One relation of a query: a name and a DataFrame whose columns are its attributes.

    key: columns known to be unique together; if all are attributes, no duplicates need to be removed."""

    name: str
    df: DataFrame | None
    attrs: tuple[str, ...]
    key: tuple[str, ...] | None = None

    @classmethod
    def of(cls, name: str, df: DataFrame, columns: dict[str, str] | None = None, key: tuple[str, ...] | None = None) -> Atom:
        """columns: attribute -> column of df; all columns under their own names if omitted."""
        columns = columns or {c: c for c in df.columns}
        return cls(name, df.select(*[F.col(c).alias(a) for a, c in columns.items()]), tuple(columns), key)


@dataclass
class JoinQuery:
    """Natural join of atoms. After binding, attributes shared by two or more atoms hold no nulls and have one type everywhere."""

    atoms: list[Atom]
    filters: list[tuple[str, str]] = field(default_factory=list)

    def __post_init__(self):
        if twice := [n for n, k in Counter(a.name for a in self.atoms).items() if k > 1]:
            raise ValueError(f"atom names must differ: {twice}")

    @classmethod
    def parse(cls, text: str, tables: dict[str, DataFrame] | None = None) -> JoinQuery:
        """'R(A,B), S(B,C)': the columns of each table are taken in order; a repeated table becomes R, R__2, ..."""
        atoms, seen = [], Counter()
        for name, inner in re.findall(r"(\w+)\s*\(([^)]*)\)", text):
            attrs = tuple(x.strip() for x in inner.split(",") if x.strip())
            seen[name] += 1
            own = name if seen[name] == 1 else f"{name}__{seen[name]}"
            df = tables[name].toDF(*attrs) if tables else None
            atoms.append(Atom(own, df, attrs))
        if not atoms:
            raise ValueError(f"no atom in {text!r}")
        return cls(atoms)

    @property
    def shared(self) -> frozenset[str]:
        """Attributes of two or more atoms."""
        return frozenset(a for a, k in Counter(x for atom in self.atoms for x in set(atom.attrs)).items() if k > 1)

    @property
    def attributes(self) -> list[str]:
        return sorted({x for a in self.atoms for x in a.attrs})

    def atom(self, name: str) -> Atom:
        return next(a for a in self.atoms if a.name == name)

    def validate(self, allow_float_keys: bool = False) -> None:
        """Rejects join attributes that can't be compared by equality."""
        for atom in self.atoms:
            for f in atom.df.schema:
                if f.name in self.shared:
                    if isinstance(f.dataType, (T.MapType, T.VariantType)):
                        raise ValueError(f"{atom.name}.{f.name}: {f.dataType.simpleString()} can't be joined on")
                    if isinstance(f.dataType, (T.DoubleType, T.FloatType)) and not allow_float_keys:
                        raise ValueError(f"{atom.name}.{f.name}: floating keys need allow_float_keys; cast to a decimal")

    def bound(self, bag: bool = False, allow_float_keys: bool = False) -> dict[str, DataFrame]:
        """Relation of each atom: attributes cast to their widest type, nulls dropped where shared, set semantics, or with bag=True one column
        __m_<atom> with the multiplicity of each tuple."""
        self.validate(allow_float_keys)
        widest: dict[str, T.DataType] = {}
        for atom in self.atoms:
            for f in atom.df.schema:
                if f.name in self.shared:
                    widest[f.name] = _wider(widest.get(f.name), f.dataType, f.name)
        out = {}
        for atom in self.atoms:
            df = atom.df
            for f in df.schema:
                if f.name in widest and f.dataType != widest[f.name]:
                    df = df.withColumn(f.name, F.col(f.name).cast(widest[f.name]))
            for attr, condition in self.filters:
                if attr in atom.attrs:
                    df = df.where(condition)
            df = df.na.drop(subset=[c for c in atom.attrs if c in self.shared]) if self.shared & set(atom.attrs) else df
            if bag:
                df = df.groupBy(*atom.attrs).agg(F.count("*").alias(f"__m_{atom.name}"))
            elif not (atom.key and set(atom.key) <= set(atom.attrs)):
                df = df.dropDuplicates()
            out[atom.name] = df
        return out

    def filtered(self, attr: str, condition: str) -> JoinQuery:
        """The query with a condition on one attribute, applied to every atom that has it."""
        if attr not in self.attributes:
            raise ValueError(f"no attribute {attr!r}")
        return replace(self, filters=[*self.filters, (attr, condition)])

    def sql(self) -> str:
        """DuckDB text of the join over views named like the atoms."""
        return "SELECT DISTINCT " + ", ".join(self.attributes) + " FROM " + " NATURAL JOIN ".join(a.name for a in self.atoms)


def _wider(a: T.DataType | None, b: T.DataType, name: str) -> T.DataType:
    if a is None or a == b:
        return b
    if isinstance(a, _NUMERIC) and isinstance(b, _NUMERIC):
        return max((a, b), key=lambda t: _NUMERIC.index(type(t)))
    if isinstance(a, T.DecimalType) and isinstance(b, T.DecimalType):
        scale = max(a.scale, b.scale)
        return T.DecimalType(min(38, max(a.precision - a.scale, b.precision - b.scale) + scale), scale)
    raise ValueError(f"attribute {name!r} is {a.simpleString()} and {b.simpleString()}")
