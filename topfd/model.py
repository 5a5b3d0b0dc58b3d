"""Relations, attribute sets and dependencies.

An attribute set is an int bitmask over a frozen column order. Rows stay in a DataFrame; what reaches the driver are numbers of classes and
a bounded number of row pairs as bitmasks.

Settled questions, each with a test:

* Rows are a bag: n is the row count, and repeated rows add redundancy.
* Nulls equal each other and differ from every value (``nulls="eq"``). With ``nulls="neq"`` a row with a null in a set is a class of its own there.
* NaN equals NaN and -0.0 equals 0.0, as in Spark's grouping.
* The empty set has one class (none if there is no row), so a constant column is determined by it and by nothing larger; ``empty_lhs=False`` leaves it out.
* Dependencies with redundancy 0 are never in a top-k answer, so the threshold starts at 1.
* Ties are broken by a total order: redundancy descending, then fewer attributes, then the sorted names joined by commas, then the right-hand
  side. ``ties="any"`` prunes at equality as well and only fixes the redundancies.
* Fewer than k dependencies give fewer rows; k below 1 is an error.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Row
from pyspark.sql import functions as F
from pyspark.sql import types as T

FD_SCHEMA = "rank int, lhs array<string>, lhs_text string, rhs string, lhs_size int, redundancy long, n_rows long, n_classes long, redundancy_ratio double"
STATS_SCHEMA = (
    "variant string, k int, n_rows long, n_attributes int, status string, nodes_generated long, nodes_visited long, validations long, valid_found long, "
    "valid_until_last_change long, pruned_expand long, pruned_validate long, pruned_pop long, edges long, sample_refuted long, slice_refuted long, rounds long, spark_jobs long, wall_s double, "
    "pairs_s double, queue_s double, peak_heap_mb double, stages long, shuffle_mb double, rows_read long, peak_task_mb double, exact boolean"
)
TRACE_SCHEMA = "seq long, elapsed_s double, validations long, tau long"


#: Bytes of a split of the input, and from where on Spark's estimate of a table's size means that it knows none.
SPLIT_BYTES, UNKNOWN_SIZE = 128 << 20, 1 << 62
#: Bytes of the input for which kept codes get a task of their own, where the input itself is read by fewer tasks than there are cores.
DEALT_BYTES = 1 << 20

#: Types of which a value takes no more room than a code.
SMALL = (T.ByteType, T.ShortType, T.IntegerType, T.LongType, T.BooleanType, T.DateType, T.TimestampType, T.TimestampNTZType, T.FloatType, T.DoubleType)


def bits(mask: int) -> Iterator[int]:
    """Positions of the set bits, ascending."""
    while mask:
        low = mask & -mask
        yield low.bit_length() - 1
        mask ^= low


def mask_of(names: list[str] | tuple[str, ...], columns: list[str]) -> int:
    return sum(1 << columns.index(c) for c in set(names))


@dataclass(frozen=True)
class FD:
    lhs: int
    rhs: int
    n_classes: int
    n_rows: int

    @property
    def redundancy(self) -> int:
        return self.n_rows - self.n_classes


@dataclass(frozen=True)
class Limits:
    """A run ends with status over_budget beyond any of these; its answer is then what it had found."""

    max_validations: int | None = None
    max_nodes: int | None = None
    max_seconds: float | None = None
    max_antichain: int | None = None


@dataclass
class Relation:
    """A DataFrame with a frozen order of attributes. Only these columns are read, and each job only the ones it needs. coded: two 64-bit codes of each value.
    stored: what Spark keeps of kept rows, the values where they are no larger than a code.
    counted: rows, and classes of each attribute, once a search knows them. shared: where it is a dictionary, profile and evidence are prepared by the first search and kept
    there for later ones of the same rows, which count the seconds of the preparation as theirs. hold: a search holds the rows whole on the driver if they are few enough;
    held: these rows, while a search runs. holds: what was held and the seconds that it took, until the relation is released. columns_held: attributes
    that are held once for several relations over some of them. rows: the same rows kept by Spark."""

    df: DataFrame
    columns: list[str]
    nulls: str = "eq"
    coded: DataFrame | None = None
    kept: bool = False
    stored: DataFrame | None = None
    counted: tuple[int, list[int]] | None = None
    shared: dict | None = None
    hold: bool = False
    held: object | None = None
    holds: tuple[object | None, float] | None = None
    columns_held: object | None = None
    rows: DataFrame | None = None
    _partitions: int | None = None

    @classmethod
    def bind(cls, df: DataFrame, columns: list[str] | None = None, nulls: str = "eq", persist: bool = False) -> Relation:
        """persist: keep the codes (they may spill to disk) while a search runs; for views that are costly to recompute."""
        if nulls not in ("eq", "neq"):
            raise ValueError("nulls is 'eq' or 'neq'")
        columns = list(df.columns if columns is None else columns)
        if missing := [c for c in columns if c not in df.columns]:
            raise ValueError(f"no such columns: {missing}")
        if len(set(columns)) < len(columns):
            raise ValueError("attributes need different names")
        narrow = df.select(*[_canonical(f).alias(f.name) for f in (df.schema[c] for c in columns)])
        rel = cls(narrow, columns, nulls, None, persist)
        if persist:
            parts, stored = rel._dealt(), rel._stored()
            rel.stored = (stored.repartition(parts) if parts > 1 else stored).persist()
            rel.coded = rel._codes_of_stored()
        else:
            rel.coded = rel.codes_of(narrow)
        return rel

    def _small(self) -> list[bool]:
        """Of which attributes the values are kept, from which codes follow whenever they are read; of all others, two codes. Where nulls differ from each other, codes are kept."""
        return [self.nulls == "eq" and isinstance(f.dataType, SMALL) for f in (self.df.schema[c] for c in self.columns)]

    def _stored(self) -> DataFrame:
        small = self._small()
        return self.df.select(*[c for i in range(self.m) for c in ([self.col(i).alias(f"_0_{i}")] if small[i] else [self._code(i, seed).alias(f"_{seed}_{i}") for seed in (1, 2)])])

    def _codes_of_stored(self) -> DataFrame:
        small = self._small()
        return self.stored.select(*[(_hash(F.col(f"_0_{i}"), seed=seed) if small[i] else F.col(f"_{seed}_{i}")).alias(f"_{seed}_{i}") for i in range(self.m) for seed in (1, 2)])

    def codes_of(self, rows: DataFrame) -> DataFrame:
        return rows.select(*[self._code(i, seed).alias(f"_{seed}_{i}") for i in range(self.m) for seed in (1, 2)])

    def keep_rows(self, mark: str | None = None) -> DataFrame:
        """The rows, kept once and dealt out. mark: a column of this name has a hash of each row."""
        if self.rows is None:
            parts = self._dealt()
            rows = self.df if mark is None else self.df.withColumn(mark, F.xxhash64(*[x for i in range(self.m) for x in (self.col(i).isNull(), self.col(i))]))
            self.rows = (rows.repartition(parts) if parts > 1 else rows).persist()
        return self.rows

    def _bytes(self) -> int:
        """Of the tables below, as far as Spark knows them. Nothing runs."""
        leaves = self.df._jdf.queryExecution().optimizedPlan().collectLeaves()
        sizes = [int(leaves.apply(i).stats().sizeInBytes()) for i in range(leaves.size())]
        return sum(x for x in sizes if x < UNKNOWN_SIZE)

    def partitions(self) -> int:
        """About as many as the tables below are read in: their size over that of a split."""
        if self._partitions is None:
            self._partitions = max(1, self._bytes() // SPLIT_BYTES)
        return self._partitions

    def _dealt(self) -> int:
        """Tasks that kept codes are dealt out to, 1 to leave them as they are read: a file of one row group is read by one task, and so would be each branch of a job."""
        cores = self.df.sparkSession.sparkContext.defaultParallelism
        if self.partitions() >= cores or len(self.df.inputFiles()) >= cores:
            return 1
        return min(cores, -(-self._bytes() // DEALT_BYTES))

    def release(self) -> None:
        self.held = self.shared = self.holds = self.columns_held = None
        if self.rows is not None:
            self.rows.unpersist()
            self.rows = None
        if self.stored is not None:
            self.stored.unpersist()

    @property
    def m(self) -> int:
        return len(self.columns)

    def col(self, i: int) -> Column:
        return F.col(f"`{self.columns[i]}`")

    def cols(self, mask: int) -> list[Column]:
        return [self.col(i) for i in bits(mask)]

    def names(self, mask: int) -> list[str]:
        return sorted(self.columns[i] for i in bits(mask))

    def lhs_text(self, mask: int) -> str:
        return ",".join(self.names(mask))

    def sort_key(self, fd: FD) -> tuple:
        """Ascending in the canonical order of answers."""
        return (-fd.redundancy, fd.lhs.bit_count(), self.lhs_text(fd.lhs).encode(), self.columns[fd.rhs].encode())

    def fingerprint(self, mask: int, seed: int) -> Column:
        """64 bits of a row's values in these columns; equal for equal values, null included. A leading position keeps null apart from shifted values."""
        return _hash(*self.cols(mask), seed=seed)

    def _code(self, i: int, seed: int) -> Column:
        """Of one value. Where nulls differ from everything, each has a code of its own row; classes with more than one row then hold none, so their keys don't depend on it."""
        code = self.fingerprint(1 << i, seed)
        if self.nulls == "neq":
            code = F.when(self.col(i).isNull(), F.xxhash64(F.monotonically_increasing_id(), F.lit(i), F.lit(seed))).otherwise(code)
        return code

    def key_sql(self, mask: int) -> tuple[str, str]:
        """128 bits of a coded row's values in these columns: its class, without the values."""
        return tuple(f"xxhash64({', '.join([str(mask.bit_count()), *(f'_{seed}_{i}' for i in bits(mask))])})" for seed in (1, 2))

    def key(self, mask: int) -> tuple[Column, Column]:
        return tuple(map(F.expr, self.key_sql(mask)))

    def frame(self, fds: list[FD]) -> DataFrame:
        """Dependencies, in canonical order, as rows of FD_SCHEMA."""
        ordered = sorted(fds, key=self.sort_key)
        rows = [
            Row(r, self.names(f.lhs), self.lhs_text(f.lhs), self.columns[f.rhs], f.lhs.bit_count(), f.redundancy, f.n_rows, f.n_classes, f.redundancy / f.n_rows if f.n_rows else 0.0)
            for r, f in enumerate(ordered, 1)
        ]
        return self.df.sparkSession.createDataFrame(rows, FD_SCHEMA)


def _hash(*columns: Column, seed: int) -> Column:
    return F.xxhash64(F.lit(seed), *[x for c in columns for x in (c.isNull(), c)])


def _canonical(f: T.StructField) -> Column:
    """A form that grouping and hashing accept: maps as sorted entries, variants as JSON; zeros of one sign."""
    c = F.col(f"`{f.name}`")
    if isinstance(f.dataType, T.MapType):
        return F.array_sort(F.map_entries(c))
    if f.dataType.typeName() == "variant":
        return F.to_json(c)
    if isinstance(f.dataType, (T.DoubleType, T.FloatType)):
        return F.when(c == 0, F.lit(0.0).cast(f.dataType)).otherwise(c)
    return c
