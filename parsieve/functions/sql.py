"""The search's questions as SQL functions, and a table function for children of a set."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from parsieve.functions.bitset import members

#: name -> definition. Lists are arrays of struct<parents array<string>, score double>.
FUNCTIONS = {
    "ps_contains": "(whole array<string>, part array<string>) returns boolean return size(array_except(part, whole)) = 0",
    "ps_names": "(bits bigint, names array<string>) returns array<string> return array_sort(filter(transform(names, (c, i) -> if(bits & shiftleft(1L, i) <> 0, c, null)), c -> c is not null))",
    "ps_best_score": "(lists array<struct<parents: array<string>, score: double>>, pool array<string>) returns double return array_min(transform(filter(lists, x -> size(array_except(x.parents, pool)) = 0), x -> x.score))",
    "ps_entropy": """(counts array<bigint>) returns double return if(size(filter(counts, c -> c > 0)) = 0, 0.0D, log2(aggregate(counts, 0L, (a, c) -> a + c))
      - aggregate(filter(counts, c -> c > 0), 0.0D, (a, c) -> a + c * log2(c)) / aggregate(counts, 0L, (a, c) -> a + c))""",
}


@udtf(returnType="new int, bits bigint, targets bigint")
class PsChildren:
    """Nodes that have the set `bits` of n columns as their chosen predecessor."""

    def eval(self, bits: int, targets: int, n: int):
        for i in range(int(bits).bit_length(), n):
            left = targets & ~(1 << i)
            if left and i not in members(bits):
                yield i, bits | 1 << i, left


def register(spark: SparkSession) -> None:
    """Makes the functions known to a session, as temporary ones."""
    for name, body in FUNCTIONS.items():
        spark.sql(f"create or replace temporary function {name} {body}")
    spark.udtf.register("ps_children", PsChildren)
