"""Predicates as views over tables: base (a table or join), one SQL expression for each position, and a condition.

The SQL is common to Spark and DuckDB. Table names stand in braces. Predicates with equal base and columns can
be read in one scan. A row with a NULL position is no fact and is left out (null_policy "drop").
"""

from __future__ import annotations

import json
import re
from collections.abc import Mapping as AbcMapping
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

from ontospark.plans.lineage import cut

#: Types that a position may have; doubles only where the position is never joined or compared.
JOINABLE = (T.LongType, T.IntegerType, T.ShortType, T.ByteType, T.StringType, T.BooleanType, T.DateType, T.TimestampType, T.DecimalType)


class TypeClash(TypeError):
    pass


@dataclass(frozen=True)
class Predicate:
    name: str
    base: str
    columns: tuple[str, ...]
    where: str = "true"
    unique: bool = False  # the columns hold a key of the base, so rows are distinct as they are

    @property
    def derived(self) -> bool:
        """Whether the base is more than a scan: a join, a window or an aggregate."""
        return bool(re.search(r"\b(JOIN|SELECT)\b", self.base, re.IGNORECASE))

    def sql(self, null_policy: str = "drop") -> str:
        cols = ", ".join(f"{e} AS c{i}" for i, e in enumerate(self.columns, 1))
        cond = [self.where] + [f"({e}) IS NOT NULL" for e in self.columns if null_policy == "drop"]
        return f"SELECT {'' if self.unique else 'DISTINCT '}{cols} FROM {self.base} WHERE {' AND '.join(f'({c})' for c in cond if c != 'true') or 'true'}"


class Mapping(AbcMapping):
    """Predicate name -> Predicate. Names without an entry have no extension."""

    def __init__(self, *predicates: Predicate):
        self.by = {p.name: p for p in predicates}

    def __getitem__(self, k: str) -> Predicate:
        return self.by[k]

    def __iter__(self):
        return iter(self.by)

    def __len__(self) -> int:
        return len(self.by)

    def edb(self) -> frozenset[str]:
        return frozenset(self.by)

    def to_json(self) -> str:
        return json.dumps([p.__dict__ for p in self.by.values()])

    @staticmethod
    def from_json(text: str) -> Mapping:
        return Mapping(*(Predicate(**{**p, "columns": tuple(p["columns"])}) for p in json.loads(text)))


class Database:
    """Predicate extensions over Parquet tables of one folder, or readers of any format, or given DataFrames."""

    def __init__(self, spark: SparkSession, mapping: Mapping, path: str | None = None, fmt: str = "parquet", options: dict | None = None, extensions: dict[str, DataFrame] | None = None, null_policy: str = "drop"):
        self.spark, self.mapping, self.path, self.fmt, self.options = spark, mapping, path, fmt, options or {}
        self.extensions, self.null_policy = dict(extensions or {}), null_policy
        self.tables: dict[str, DataFrame] = {}
        self.made: dict[str, DataFrame] = {}
        self.kinds: dict[str, list[T.DataType]] = {}

    def table(self, name: str) -> DataFrame:
        if name not in self.tables:
            suffix = ".parquet" if self.fmt == "parquet" else f".{self.fmt}"
            self.tables[name] = self.spark.read.format(self.fmt).options(**self.options).load(f"{self.path}/{name}{suffix}")
        return self.tables[name]

    def __contains__(self, pred: str) -> bool:
        return pred in self.extensions or pred in self.mapping

    def edb(self) -> frozenset[str]:
        return frozenset(self.extensions) | self.mapping.edb()

    def run(self, sql: str) -> DataFrame:
        names = set(re.findall(r"\{(\w+)\}", sql))
        return self.spark.sql(sql, **{n: self.table(n) for n in names})

    def extension(self, pred: str) -> DataFrame:
        """Distinct facts as columns c1, c2, ..."""
        if pred not in self.made:
            if pred in self.extensions:
                df = self.extensions[pred]
                self.made[pred] = df.toDF(*[f"c{i}" for i in range(1, len(df.columns) + 1)])
            else:
                self.made[pred] = self.run(self.mapping[pred].sql(self.null_policy))
        return self.made[pred]

    def share(self, uses: dict[str, int]) -> None:
        """Write the extensions of derived predicates that several plans use, once; later plans read the files."""
        for pred, n in uses.items():
            if n > 1 and pred in self.mapping and pred not in self.extensions and self.mapping[pred].derived and not (df := self.extension(pred)).isStreaming:
                self.extensions[pred] = self.made[pred] = cut(df)

    def extended(self, views: dict[str, DataFrame]) -> Database:
        """The same database with further predicates."""
        out = Database(self.spark, self.mapping, self.path, self.fmt, self.options, {**self.extensions, **views}, self.null_policy)
        out.tables, out.made, out.kinds = self.tables, dict(self.made), dict(self.kinds)
        return out

    def scan(self, preds: list[str]) -> list[tuple[list[str], DataFrame]]:
        """Extensions of several predicates of one arity; those over equal base and columns come from one scan."""
        groups: dict[tuple, list[str]] = {}
        for p in preds:
            key = (p,) if p in self.extensions else (self.mapping[p].base, self.mapping[p].columns)
            groups.setdefault(key, []).append(p)
        out = []
        for key, names in groups.items():
            if len(names) == 1:
                out.append((names, self.extension(names[0])))
            else:
                any_ = " OR ".join(f"({self.mapping[n].where})" for n in names)
                out.append((names, self.run(Predicate("+".join(names), key[0], key[1], any_, all(self.mapping[n].unique for n in names)).sql(self.null_policy))))
        return out

    def types(self, pred: str) -> list[T.DataType]:
        if pred not in self.kinds:
            self.kinds[pred] = [f.dataType for f in self.extension(pred).schema.fields]
        return self.kinds[pred]

    def check_types(self, atoms) -> None:
        """Refuse a variable that stands at positions of different types, or joins doubles."""
        from ontospark.logic.terms import Const, Var

        whole = (T.LongType, T.IntegerType, T.ShortType, T.ByteType)
        seen: dict = {}
        for a in atoms:
            if a.pred not in self or not a.args:
                continue
            for t, kind in zip(a.args, self.types(a.pred), strict=True):
                if isinstance(t, Const) and not isinstance(kind, JOINABLE):
                    raise TypeClash(f"{a}: a constant is compared with {kind.simpleString()}")
                if not isinstance(t, Var):
                    continue
                if t in seen:
                    other = seen[t]
                    if not isinstance(kind, JOINABLE) or (kind != other and not (isinstance(kind, whole) and isinstance(other, whole))):
                        raise TypeClash(f"{a}: {t} is {other.simpleString()} elsewhere and {kind.simpleString()} here")
                seen[t] = kind
