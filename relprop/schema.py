"""Relational schema: tables, foreign keys, column kinds, catalogs and prediction tasks.

A table is a node type, a row a node, a foreign key an edge type.  Nothing here touches data but ``validate``.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class ForeignKey:
    """Column ``column`` of ``src`` refers to the key of ``dst``.  Several keys between two tables are distinct."""

    src: str
    column: str
    dst: str

    @property
    def name(self) -> str:
        return f"{self.src}.{self.column}"


@dataclass(frozen=True)
class TableSpec:
    name: str
    key: tuple[str, ...]
    numeric: tuple[str, ...] = ()
    categorical: tuple[str, ...] = ()
    #: Columns that mean the same thing share a domain, and so a dictionary and its vectors.
    domains: tuple[tuple[str, str], ...] = ()

    def domain(self, column: str) -> str:
        return dict(self.domains).get(column, f"{self.name}.{column}")

    @property
    def features(self) -> tuple[str, ...]:
        return self.numeric + self.categorical


@dataclass
class Catalog:
    """Specs, foreign keys and lazy frames.  A frame may have more columns than its spec names."""

    specs: dict[str, TableSpec]
    fks: tuple[ForeignKey, ...]
    frames: dict[str, DataFrame] = field(default_factory=dict)

    @classmethod
    def build(cls, specs: list[TableSpec], fks: list[ForeignKey], frames: dict[str, DataFrame] | None = None) -> Catalog:
        by_name = {s.name: s for s in specs}
        for fk in fks:
            for end in (fk.src, fk.dst):
                if end not in by_name:
                    raise ValueError(f"foreign key {fk.name} names an unknown table {end}")
            if len(by_name[fk.dst].key) > 1:
                raise ValueError(f"foreign key {fk.name} is one column, the key of {fk.dst} has several: give {fk.dst} a key of one column")
        if len({fk.name for fk in fks}) != len(fks):
            raise ValueError("a column can carry one foreign key only")
        return cls(by_name, tuple(fks), dict(frames or {}))

    def forward(self, table: str) -> list[ForeignKey]:
        """Multiset of forward relations of a table, in order of declaration."""
        return [fk for fk in self.fks if fk.src == table]

    def backward(self, table: str) -> list[ForeignKey]:
        """Multiset of relations that refer to a table."""
        return [fk for fk in self.fks if fk.dst == table]

    def key(self, table: str) -> tuple[str, ...]:
        return self.specs[table].key

    def frame(self, table: str) -> DataFrame:
        return self.frames[table]

    def without(self, table: str, column: str) -> Catalog:
        """The same catalog where a column (the label) is no feature of its table."""
        s = self.specs[table]
        kept = replace(s, numeric=tuple(c for c in s.numeric if c != column), categorical=tuple(c for c in s.categorical if c != column))
        return Catalog(self.specs | {table: kept}, self.fks, self.frames)

    def with_frames(self, frames: dict[str, DataFrame]) -> Catalog:
        return Catalog(self.specs, self.fks, self.frames | frames)

    def permuted(self, order: list[int]) -> Catalog:
        """Edges in another order; what propagation returns must not depend on it."""
        return Catalog(dict(reversed(self.specs.items())), tuple(self.fks[i] for i in order), self.frames)

    def validate(self) -> list[str]:
        """Problems found by one job a key and one a foreign key: keys that repeat or are null, references to nothing."""
        found = []
        for name, spec in self.specs.items():
            df = self.frame(name)
            null = F.coalesce(F.sum(F.when(F.greatest(*[F.col(k).isNull().cast("int") for k in spec.key], F.lit(0)) > 0, 1)), F.lit(0))
            n, nulls = df.agg(F.count("*"), null).first()
            distinct = df.select(*spec.key).distinct().count()
            if n != distinct:
                found.append(f"{name}: {n - distinct} rows repeat a key")
            if nulls:
                found.append(f"{name}: {nulls} rows have no key")
        for fk in self.fks:
            orphans = self.frame(fk.src).filter(F.col(fk.column).isNotNull()).join(self.frame(fk.dst).select(F.col(self.key(fk.dst)[0]).alias("_k")), F.col(fk.column) == F.col("_k"), "left_anti").count()
            if orphans:
                found.append(f"{fk.name}: {orphans} rows refer to nothing in {fk.dst}")
        return found


@dataclass
class Task:
    """Predict ``label`` of ``target``.  The label column is in the target's frame and in no feature list."""

    catalog: Catalog
    target: str
    label: str = "label"
    kind: str = "binary"  # or "multiclass", "regression"
    classes: int = 1
    ratios: tuple[float, float, float] = (0.6, 0.2, 0.2)
    name: str = "task"

    def __post_init__(self):
        self.catalog = self.catalog.without(self.target, self.label)

    @property
    def keys(self) -> tuple[str, ...]:
        return self.catalog.key(self.target)

    def rows(self, seed: int = 0) -> DataFrame:
        """Key columns, label and part (train, valid or test)."""
        df = self.catalog.frame(self.target)
        return df.select(*self.keys, F.col(self.label), part_of(list(self.keys), seed, self.ratios).alias("part"))


def bucket_of(columns: list[str], seed: int = 0, modulus: int = 1000) -> Column:
    """A number below ``modulus`` from md5 of seed and key; SQL engines agree on it."""
    text = F.concat_ws(":", F.lit(str(seed)), *[F.col(c).cast("string") for c in columns])
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long") % modulus


def part_of(columns: list[str], seed: int = 0, ratios: tuple[float, float, float] = (0.6, 0.2, 0.2)) -> Column:
    b, a = bucket_of(columns, seed), round(1000 * ratios[0])
    return F.when(b < a, "train").when(b < a + round(1000 * ratios[1]), "valid").otherwise("test")


def infer_catalog(frames: dict[str, DataFrame], keys: dict[str, str]) -> Catalog:
    """A proposal from names and types: a column that ends like a key of another table refers to it."""
    fks, specs = [], []
    for name, df in frames.items():
        kinds = dict(df.dtypes)
        stem = lambda c: c.split("_", 1)[-1]
        own = keys[name]
        for c in kinds:
            for other, k in keys.items():
                if c != own and stem(c) == stem(k) and kinds[c] in ("int", "bigint"):
                    fks.append(ForeignKey(name, c, other))
        used = {own, *(fk.column for fk in fks if fk.src == name)}
        specs.append(TableSpec(name, (own,), tuple(c for c, t in kinds.items() if c not in used and t in ("double", "float", "int", "bigint")), tuple(c for c, t in kinds.items() if c not in used and t == "string" and "name" not in c)))
    return Catalog.build(specs, fks, frames)


#: Date columns of the star tables; each stands for four categories, its year, month, day and weekday.
DATES = {"orders": "o_orderdate", "lineitem": "l_shipdate", "events": "ts"}
DATE_PARTS = ("year", "month", "day", "weekday")


def dated(spec: TableSpec) -> TableSpec:
    """A star table's spec with the parts of its date as categories."""
    c = DATES.get(spec.name)
    return replace(spec, categorical=spec.categorical + tuple(f"{c}_{p}" for p in DATE_PARTS)) if c else spec


def read_dated(spark: SparkSession, folder: str, names: list[str]) -> dict[str, DataFrame]:
    """The tables, with the parts of their dates as text."""
    from .features import expand_dates

    out = {}
    for n, df in read_tables(spark, folder, names).items():
        if c := DATES.get(n):
            df = expand_dates(df, [c])
            df = df.withColumns({f"{c}_{p}": F.col(f"{c}_{p}").cast("string") for p in DATE_PARTS})
        out[n] = df
    return out


def read_tables(spark: SparkSession, folder: str, names: list[str], fmt: str = "parquet") -> dict[str, DataFrame]:
    return {n: spark.read.format(fmt).load(f"{folder}/{n}.{fmt}") for n in names}


# Catalogs over the given star-schema tables.

STAR_SPECS = [
    TableSpec("region", ("r_regionkey",), (), ("r_name",)),
    TableSpec("nation", ("n_nationkey",), (), ("n_name",)),
    TableSpec("customer", ("c_custkey",), ("c_acctbal",), ("c_mktsegment",)),
    TableSpec("supplier", ("s_suppkey",), ("s_acctbal",)),
    TableSpec("part", ("p_partkey",), ("p_size", "p_retailprice"), ("p_brand", "p_type")),
    TableSpec("orders", ("o_orderkey",), ("o_totalprice",), ("o_orderstatus", "o_orderpriority"), (("o_orderstatus", "status"),)),
    TableSpec("lineitem", ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"), ("l_quantity", "l_extendedprice", "l_discount", "l_tax"), ("l_returnflag", "l_linestatus"), (("l_linestatus", "status"),)),
    TableSpec("events", ("event_id",), ("value",), ("event_type",)),
]
STAR_FKS = [
    ForeignKey("nation", "n_regionkey", "region"),
    ForeignKey("customer", "c_nationkey", "nation"),
    ForeignKey("supplier", "s_nationkey", "nation"),
    ForeignKey("orders", "o_custkey", "customer"),
    ForeignKey("lineitem", "l_orderkey", "orders"),
    ForeignKey("lineitem", "l_partkey", "part"),
    ForeignKey("lineitem", "l_suppkey", "supplier"),
    ForeignKey("events", "user_id", "customer"),
]


def star_catalog(spark: SparkSession, folder: str, tables: list[str] | None = None, dates: bool = False) -> Catalog:
    """The eight-table catalog, or the part of it over ``tables``; with ``dates``, date parts are features."""
    names = tables or [s.name for s in STAR_SPECS]
    specs = [dated(s) if dates else s for s in STAR_SPECS if s.name in names]
    fks = [k for k in STAR_FKS if k.src in names and k.dst in names]
    return Catalog.build(specs, fks, (read_dated if dates else read_tables)(spark, folder, names))


def kept(df: DataFrame) -> DataFrame:
    """Written once to the checkpoint folder where one is set, else kept by the block manager."""
    sc = df.sparkSession.sparkContext
    if sc._jsc.sc().getCheckpointDir().isDefined():
        return df.checkpoint()
    return df.persist()


Builder = Callable[[SparkSession, str], Task]
