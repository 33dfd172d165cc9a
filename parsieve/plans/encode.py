"""From a DataFrame of labels to a compressed table of codes, and its facts."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, MapType, StructType

MOST_STATES = 4096
LOCAL_ROWS = 300_000
#: Bytes of a coded table, four for each code, whose facts the driver takes from the codes.
LOCAL_CODES = 128 << 20


@dataclass
class Encoded:
    """Columns in search order with their facts. `rows`: codes and the weight w of each
    distinct row. Bits: m * H(t), m * H(t | all others)."""

    rows: DataFrame
    order: list[str]
    arity: list[int]
    labels: dict[str, list]
    m: int
    entropy: list[float]
    floor: list[float]
    local: pa.Table | None = field(default=None, repr=False)  # the rows, where the driver has them

    @property
    def n(self) -> int:
        return len(self.order)

    def packed(self, most_bytes: int = 512 << 20) -> tuple[np.ndarray, np.ndarray]:
        """Codes (column by column) and weights for broadcasting; size checked first."""
        distinct = self.local.num_rows if self.local is not None else self.rows.count()
        width = 1 if max(self.arity, default=1) <= 256 else 2
        if distinct * (self.n * width + 8) > most_bytes:
            raise MemoryError("the compressed table is too large to broadcast: use backend='relational'")
        t = self.local if self.local is not None else self.rows.select(*(f"`{c}`" for c in self.order), "w").toArrow()
        kind = np.uint8 if width == 1 else np.uint16
        return np.stack([t.column(c).to_numpy().astype(kind) for c in self.order]) if self.n else np.zeros((0, distinct), kind), t.column("w").to_numpy().astype(np.int64)


def quantile_bins(df: DataFrame, column: str, k: int, error: float = 0.001) -> Column:
    """Bin number by breakpoints fixed now, so that later uses agree."""
    cuts = sorted(set(df.approxQuantile(column, [i / k for i in range(1, k)], error)))
    return sum((F.when(F.col(column) >= c, 1).otherwise(0) for c in cuts), F.lit(0))


def code_log_sum(df: DataFrame, weight: str = "w") -> Column:
    return F.sum(F.col(weight) * F.log2(weight))


def encode(df: DataFrame, variables: list[str] | None = None, null_policy: str = "state", order: str = "arity", weight: str | None = None) -> Encoded:
    """Dictionary codes, one aggregation to distinct rows (the only pass over raw rows),
    then the facts from those. A null is a state of its own, dropped, or an error. With a
    `weight` column a row stands for so many; rows of weight 0 or less count for nothing."""
    variables = variables or [c for c in df.columns if c != weight]
    number = F.sum(F.col(weight).cast("long")) if weight else F.count(F.lit(1))
    if weight:
        df = df.where(F.col(weight) > 0)
    if null_policy == "drop":
        df = df.dropna(subset=variables)
    sums = df.groupBy(*variables).agg(number.alias("w__")).persist()
    try:
        if variables:
            # A table of few different rows, as most are, is coded by the driver after one job.
            few = sums.limit(LOCAL_ROWS + 1).toArrow()
            if few.num_rows <= LOCAL_ROWS and not any(pa.types.is_nested(f.type) for f in few.schema):
                return _encode_few(df.sparkSession, few, variables, null_policy, order)
        return _encode(sums, variables, null_policy, order)
    finally:
        sums.unpersist()


def _local_facts(arrow, variables: list[str], arity: dict) -> tuple[dict, dict]:
    w = arrow.column("w").to_numpy().astype(np.int64)
    code = {c: arrow.column(c).to_numpy().astype(np.int64) for c in variables}

    def logs(chosen: list[str]) -> float:
        cell, size = np.zeros(len(w), np.int64), 1
        for c in chosen:
            if size * arity[c] >= 1 << 62:
                found, cell = np.unique(cell, return_inverse=True)
                size = len(found)
            cell, size = cell * arity[c] + code[c], size * arity[c]
        if size > max(1024, 2 * len(cell)):
            cell = np.unique(cell, return_inverse=True)[1]
        return count_log(np.bincount(cell, weights=w)) if len(w) else 0.0

    whole, total = logs(variables), logs([])
    return {c: total - logs([c]) for c in variables}, {c: max(0.0, logs([v for v in variables if v != c]) - whole) for c in variables}


def _spark_facts(rows: DataFrame, variables: list[str], m: int) -> tuple[dict, dict]:
    """The same sums as two unions of aggregations over the distinct rows."""

    def logs(chosen: list[str]) -> float:
        each = rows.groupBy(*chosen).agg(F.sum("w").alias("w"))
        return each.agg(code_log_sum(each)).first()[0] or 0.0

    whole, total = logs(variables), m * math.log2(m) if m else 0.0
    return {c: total - logs([c]) for c in variables}, {c: max(0.0, logs([v for v in variables if v != c]) - whole) for c in variables}


def count_log(counts: np.ndarray) -> float:
    """Sum of c * log2 c, grouped by count so that the order of cells cannot matter."""
    c, n = np.unique(counts[counts > 0], return_counts=True)
    return float((n * c * np.log2(c)).sum())


def _encode_few(spark: SparkSession, table: pa.Table, variables: list[str], null_policy: str, order: str) -> Encoded:
    labels, codes = {}, {}
    for c in variables:
        column = table.column(c).combine_chunks()
        known = pc.unique(column.drop_null())
        known = known.take(pc.sort_indices(known))
        nulls = column.null_count > 0
        if nulls and null_policy == "error":
            raise ValueError(f"column {c} has nulls")
        if len(known) + nulls > MOST_STATES:
            raise ValueError(f"column {c} has more than {MOST_STATES} states: bin it first")
        labels[c] = [None] * nulls + known.to_pylist()
        place = pc.index_in(column, value_set=known) if len(known) else pa.nulls(len(column), pa.int32())
        codes[c] = pc.fill_null(pc.add(place, int(nulls)), 0).cast(pa.int32())
    coded = pa.table(codes | {"w": table.column("w__").cast(pa.int64())})
    arity = {c: max(1, len(labels[c])) for c in variables}
    m = pc.sum(coded.column("w")).as_py() or 0
    bits, floor = _local_facts(coded, variables, arity)
    rows = spark.createDataFrame(coded) if coded.num_rows else spark.createDataFrame([], ", ".join(f"`{c}` int" for c in variables) + ", w long")
    out = _ordered(rows, variables, order, arity, labels, m, bits, floor)
    out.local = coded
    return out


def _ordered(rows: DataFrame, variables: list[str], order: str, arity: dict, labels: dict, m: int, bits: dict, floor: dict) -> Encoded:
    place = {c: i for i, c in enumerate(variables)}
    size = {c: round(floor[c] / max(m, 1), 6) for c in variables}
    rank = {"arity": lambda c: (-arity[c], size[c], c), "reverse": lambda c: (arity[c], -size[c], c), "input": place.__getitem__}[order]
    names = sorted(variables, key=rank)
    return Encoded(rows.select(*(f"`{c}`" for c in names), "w"), names, [arity[c] for c in names], labels, m, [float(bits[c]) for c in names], [float(floor[c]) for c in names])


def _task_states(sums: DataFrame, variables: list[str]) -> tuple[dict[str, pa.Array], int, int]:
    """Of each column its different values (nulls too; MOST_STATES + 2 of a task are enough to
    refuse it), the number of rows and the sum of their weights, by one pass of Arrow kernels."""
    kinds, parts = {f.name: f.dataType.simpleString() for f in sums.schema.fields}, 2 * sums.sparkSession.sparkContext.defaultParallelism
    most, places = MOST_STATES + 2, range(len(variables))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen, rows, total = [None] * len(variables), 0, 0
        for b in batches:
            rows, total = rows + b.num_rows, total + (pc.sum(b.column(len(variables))).as_py() or 0)
            for i in places:
                here = pc.unique(b.column(i))
                seen[i] = (here if seen[i] is None else pc.unique(pa.concat_arrays([seen[i], here]))).slice(0, most)
        if rows:
            lists = [pa.ListArray.from_arrays(pa.array([0, len(x)], pa.int32()), pa.concat_arrays([x])) for x in seen]
            yield pa.RecordBatch.from_arrays([*lists, pa.array([rows]), pa.array([total])], names=[*(f"s_{i}" for i in places), "rows", "total"])

    kind = ", ".join(f"s_{i} array<{kinds[c]}>" for i, c in enumerate(variables))
    found = sums.select(*(f"`{c}`" for c in variables), "w__").coalesce(parts).mapInArrow(run, f"{kind}, rows long, total long").toArrow()
    states = {c: pc.unique(pc.list_flatten(found.column(i).combine_chunks())) for i, c in enumerate(variables)}
    return states, pc.sum(found.column("rows")).as_py() or 0, pc.sum(found.column("total")).as_py() or 0


def _listed_states(sums: DataFrame, variables: list[str]) -> tuple[dict[str, list], dict[str, bool], int, int]:
    """The same by aggregations, for types without Arrow kernels: values, whether a column has nulls, rows, weights."""
    # Numbers of states first: a column with too many is refused before any list of them is made.
    facts = [F.sum("w__").alias("m"), F.count(F.lit(1)).alias("rows")]
    facts += [f for i, c in enumerate(variables) for f in (F.approx_count_distinct(c, 0.02).alias(f"d_{i}"), F.max(F.col(c).isNull()).alias(f"n_{i}"))]
    first = sums.agg(*facts).first()
    for i, c in enumerate(variables):
        if first[f"d_{i}"] > 1.1 * MOST_STATES:
            raise ValueError(f"column {c} has more than {MOST_STATES} states: bin it first")
    found = sums.agg(*(F.array_sort(F.collect_set(c)).alias(f"s_{i}") for i, c in enumerate(variables))).first()  # bounded by the check above
    return {c: list(found[f"s_{i}"]) for i, c in enumerate(variables)}, {c: bool(first[f"n_{i}"]) for i, c in enumerate(variables)}, first["rows"], first["m"] or 0


def _codes_by_task(sums: DataFrame, variables: list[str], states: dict[str, pa.Array], nulls: dict[str, bool]) -> DataFrame:
    """The code of each value, and the weight, by Arrow kernels."""
    shared = sums.sparkSession.sparkContext.broadcast([(states[c], int(nulls[c])) for c in variables])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = shared.value
        for b in batches:
            codes = [pc.fill_null(pc.add(pc.index_in(b.column(i), value_set=s), n), 0).cast(pa.int32()) if len(s) else pa.array(np.zeros(b.num_rows, np.int32)) for i, (s, n) in enumerate(known)]
            yield pa.RecordBatch.from_arrays([*codes, b.column(len(known))], names=[*variables, "w"])

    parts = 2 * sums.sparkSession.sparkContext.defaultParallelism  # many small parts would each start a task's Python
    return sums.select(*(f"`{c}`" for c in variables), "w__").coalesce(parts).mapInArrow(run, ", ".join(f"`{c}` int" for c in variables) + ", w long")


def _encode(sums: DataFrame, variables: list[str], null_policy: str, order: str) -> Encoded:
    flat = not any(isinstance(f.dataType, (ArrayType, MapType, StructType)) for f in sums.schema.fields)
    if flat:
        states, number, m = _task_states(sums, variables)
        nulls = {c: states[c].null_count > 0 for c in variables}
        states = {c: s.drop_null().take(pc.sort_indices(s.drop_null())) for c, s in states.items()}
        listed = {c: s.to_pylist() for c, s in states.items()}
    else:
        listed, nulls, number, m = _listed_states(sums, variables)
    labels, codes = {}, []
    for c in variables:
        known = listed[c]
        if nulls[c] and null_policy == "error":
            raise ValueError(f"column {c} has nulls")
        labels[c] = [None] * nulls[c] + known
        if len(labels[c]) > MOST_STATES:
            raise ValueError(f"column {c} has more than {MOST_STATES} states: bin it first")
        if not flat:
            place = F.array_position(F.array(*map(F.lit, known)), F.col(c)).cast("int") + (int(nulls[c]) - 1) if known else F.lit(0)
            codes.append(F.coalesce(place, F.lit(0)).cast("int").alias(c))
    rows = _codes_by_task(sums, variables, states, nulls) if flat else sums.select(*codes, F.col("w__").alias("w"))
    arity = {c: max(1, len(labels[c])) for c in variables}
    rows = rows.persist()
    local = rows.toArrow() if number * (4 * len(variables) + 8) <= LOCAL_CODES else None
    bits, floor = _spark_facts(rows, variables, m) if local is None else _local_facts(local, variables, arity)
    out = _ordered(rows, variables, order, arity, labels, m, bits, floor)
    out.local = local
    return out
