"""Relations, compressed relations and constraint problems as DataFrames."""

from __future__ import annotations

import json
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .functions.itemsets import as_items, spread
from .plans.staging import staged


@dataclass
class Relation:
    """A set of tuples over ordered columns of small integer codes; ``sign`` False lists the forbidden tuples instead."""

    df: DataFrame
    scope: list[str]
    name: str = "relation"
    sign: bool = True

    @staticmethod
    def of(df: DataFrame, scope: list[str] | None = None, name: str = "relation") -> Relation:
        """Distinct tuples of ``scope`` (all columns where None)."""
        scope = scope or df.columns
        return Relation(df.select(*scope).distinct(), scope, name)

    @staticmethod
    def from_parquet(spark: SparkSession, folder: str, table: str, scope: list[str]) -> Relation:
        return Relation.of(spark.read.parquet(f"{folder}/{table}.parquet"), scope, table)

    @staticmethod
    def from_query(spark: SparkSession, sql: str, **tables: DataFrame) -> Relation:
        return Relation.of(spark.sql(sql, **tables))

    @property
    def arity(self) -> int:
        return len(self.scope)

    def coded(self) -> tuple[Relation, DataFrame]:
        """Values replaced by their rank in the column's domain (null first), and the dictionary (var, code, value).

        A dictionary holds distinct values of one column; finite domains are what the methods assume, and the join is
        left to the planner, which broadcasts it only below its size limit.
        """
        df, dictionaries = self.df, []
        for i, c in enumerate(self.scope):
            values = self.df.select(F.col(c).alias("value")).distinct().select("value", (F.row_number().over(Window.orderBy(F.col("value").asc_nulls_first())) - 1).alias("code"))
            dictionaries.append(values.select(F.lit(i).alias("var"), "code", F.col("value").cast("string").alias("value")))
            df = df.join(values.withColumnsRenamed({"value": f"_{c}", "code": f"_code{i}"}), F.col(c).eqNullSafe(F.col(f"_{c}"))).drop(f"_{c}")
        coded = df.select(*[F.col(f"_code{i}").alias(c) for i, c in enumerate(self.scope)])
        return Relation(coded, self.scope, self.name, self.sign), reduce(DataFrame.unionByName, dictionaries)

    def numbered(self) -> DataFrame:
        """(tid, items): tuples in scope order with increasing, not dense numbers, written so that the numbers hold."""
        ordered = self.df.repartitionByRange(*self.scope).sortWithinPartitions(*self.scope)
        return staged(ordered.select(F.monotonically_increasing_id().alias("tid"), as_items(self.scope).alias("items")), "tuples")

    def domains(self) -> DataFrame:
        """(var, code, live) of all values in use."""
        every = self.df.select(F.explode(as_items(self.scope)).alias("x")).select(F.col("x.p").alias("var"), F.col("x.v").alias("code")).distinct()
        return every.withColumn("live", F.lit(True))

    def cells(self) -> int:
        return self.df.count() * self.arity

    def mine(self, kind: str = "maximal", s_min: int = 2, k: int | None = None, ties: str = "cut") -> DataFrame:
        """(items, len, freq): 'frequent', 'closed' or 'maximal' sets, or the 'topk' most frequent closed ones."""
        from .operators import compression, mining

        if kind == "topk":
            return mining.top(compression.candidates(self, s_min, "closed"), k or 10, ties=ties)
        return compression.candidates(self, s_min, kind)

    def compress(self, method: str = "area_cover", **options) -> CompressedRelation | DataFrame:
        """The compressed form by any method: entries ('area_cover', 'savings_slice', 'rate_tree', 'microstructure'),
        or rows and edges ('cartesian', 'wildcard', 'restricted', 'diagram', 'bitset')."""
        from .operators import compression

        if method == "bitset":
            return compression.bitset(compression.dense(self))
        if method not in ("area_cover", "savings_slice", "rate_tree", "microstructure", "cartesian", "wildcard", "restricted", "diagram"):
            raise ValueError(f"no method {method!r}")
        return getattr(compression, method)(self, **options)

    def allowed(self, domains: list[list[int]]) -> Relation:
        """The positive form of a negative table over the given values of each position: all their combinations less
        the listed ones. As large as the product of the domains, which is what a search kernel's table is; joins and
        propagation work on the listed tuples instead."""
        if self.sign:
            return self
        every = self.df.sparkSession.range(1)
        for c, codes in zip(self.scope, domains):
            every = every.select("*", F.explode(F.array(*[F.lit(v) for v in codes]).cast("array<int>")).alias(c))
        return Relation(every.select(*self.scope).join(self.df, self.scope, "left_anti"), self.scope, self.name)


@dataclass
class CompressedRelation:
    """Disjoint entries (an itemset once, and the rest of each tuple it covers) and a default table.

    ``heads`` (entry, items, len, freq), ``body`` (entry, tid, items: the residual values), ``default`` (tid, items).
    """

    scope: list[str]
    heads: DataFrame
    body: DataFrame
    default: DataFrame
    n_mined: int | None = None
    threshold: int | None = None

    @property
    def arity(self) -> int:
        return len(self.scope)

    def expand(self) -> DataFrame:
        """The relation back, as plain columns."""
        whole = self.body.join(self.heads.select("entry", F.col("items").alias("head")), "entry").select(F.array_sort(F.concat("items", "head")).alias("items"))
        return whole.unionByName(self.default.select("items")).select(*spread(F.col("items"), self.scope))

    def where(self, on: dict[int, Column]) -> DataFrame:
        """Tuples whose value at each position (var -> condition on column ``v``) fits; heads are tested before bodies are read."""

        def holds(items: Column) -> Column:
            return F.forall(items, lambda x: reduce(lambda a, b: a & b, [(x["p"] != p) | F.when(x["p"] == p, condition_on(c, x["v"])) for p, c in on.items()], F.lit(True)))

        def condition_on(build, v: Column) -> Column:
            return build(v) if callable(build) else build

        live = self.heads.where(holds(F.col("items")))
        rows = self.body.where(holds(F.col("items"))).join(live.select("entry", F.col("items").alias("head")), "entry").select(F.array_sort(F.concat("items", "head")).alias("items"))
        return rows.unionByName(self.default.where(holds(F.col("items"))).select("items")).select(*spread(F.col("items"), self.scope))

    def report(self) -> DataFrame:
        """One row of measures: tuples, cells, covered, saved, shares and means (see ``metrics``)."""
        from .plans.metrics import compression_report

        return compression_report(self)

    def write(self, path: str) -> None:
        """heads/, body/ partitioned by the number of residual columns, default/ and a manifest."""
        self.heads.write.mode("overwrite").parquet(f"{path}/heads")
        self.body.withColumn("width", F.size("items")).write.mode("overwrite").partitionBy("width").parquet(f"{path}/body")
        self.default.write.mode("overwrite").parquet(f"{path}/default")
        spark = self.heads.sparkSession
        manifest = json.dumps({"scope": self.scope, "n_mined": self.n_mined, "threshold": self.threshold})
        spark.createDataFrame([(manifest,)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest")

    @staticmethod
    def read(spark: SparkSession, path: str) -> CompressedRelation:
        m = json.loads(spark.read.text(f"{path}/manifest").first()[0])
        return CompressedRelation(m["scope"], spark.read.parquet(f"{path}/heads"), spark.read.parquet(f"{path}/body").drop("width"), spark.read.parquet(f"{path}/default"), m["n_mined"], m["threshold"])


@dataclass
class Constraint:
    """A relation laid over problem variables: position i of the relation is variable ``scope[i]``."""

    relation: Relation
    scope: list[int]


@dataclass
class Instance:
    """A constraint problem: values of each variable, and constraints (which may share relations)."""

    domains: dict[int, list[int]]
    constraints: list[Constraint]
    name: str = "instance"
    notes: dict = field(default_factory=dict)

    def _parts(self) -> list[tuple[Relation, list[int]]]:
        return [(c.relation, c.scope) for c in self.constraints]

    def domain_table(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(v, c) for v, codes in self.domains.items() for c in codes], "var int, code int")

    def propagate(self, spark: SparkSession) -> DataFrame:
        """Arc-consistent domains (var, code)."""
        from .plans import solving

        return solving.propagate(self._parts(), self.domain_table(spark))[0]

    def solve_by_join(self, spark: SparkSession) -> DataFrame:
        """All solutions within the domains, a column for each variable."""
        from .plans import solving

        return solving.by_join(self._parts(), self.domains)

    def solve(self, spark: SparkSession, methods: tuple[str, ...] = ("tabular",), time_limit_s: float = 1800.0) -> DataFrame:
        """Depth-first search. The kernel counts values from 0, so they are recoded for it and back in ``solution``."""
        from .plans import solving

        order = sorted(self.domains)
        relations, constraints = [], []
        for i, c in enumerate(self.constraints):
            sides = [sorted(self.domains[v]) for v in c.scope]
            rel = c.relation.allowed(sides)
            codes = [F.array_position(F.array(*[F.lit(v) for v in side]).cast("array<int>"), F.col(x).cast("int")) - 1 for x, side in zip(rel.scope, sides)]
            coded = rel.df.select(*[k.cast("int").alias(x) for k, x in zip(codes, rel.scope)])
            relations.append(Relation(coded.where(reduce(lambda a, b: a & b, [F.col(x) >= 0 for x in rel.scope])), rel.scope, rel.name))
            constraints.append((i, [order.index(v) for v in c.scope]))
        found = solving.search(spark, [(self.name, [len(self.domains[v]) for v in order], constraints)], relations, methods, time_limit_s)
        values = F.array(*[F.array(*[F.lit(x) for x in sorted(self.domains[v])]).cast("array<int>") for v in order])
        return found.withColumn("solution", F.transform("solution", lambda x, n: F.get(F.get(values, n), x)))
