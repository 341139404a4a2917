"""SQL surface: views of a graph, SQL functions that Catalyst sees through, a table function."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from graphdrift.functions.hashing import FACTOR, MASK, PLACE


def register_graph(spark: SparkSession, name: str, edges: DataFrame, assignment: DataFrame, history: DataFrame | None = None) -> None:
    """Views <name>_edges, <name>_assignment, <name>_room (and _history), functions mix32 and hash_part."""
    edges.createOrReplaceTempView(f"{name}_edges")
    assignment.createOrReplaceTempView(f"{name}_assignment")
    spark.sql(f"create or replace temp view {name}_room as select part, count(*) as load from {name}_assignment group by part")
    if history is not None:
        history.createOrReplaceTempView(f"{name}_history")
    fold, turn = f"((x ^ shiftright(x, 32)) & {MASK}L)", f"(((shiftright(v, 16) ^ v) * {FACTOR}) & {MASK}L)"
    spark.sql(f"create or replace temporary function mix_turn(v bigint) returns bigint return {turn}")
    spark.sql(f"create or replace temporary function mix_end(v bigint) returns bigint return shiftright(v, 16) ^ v")
    spark.sql(f"create or replace temporary function mix32(x bigint, salt bigint) returns bigint return mix_end(mix_turn(mix_turn(({fold} + salt) & {MASK}L)))")
    spark.sql(f"create or replace temporary function hash_part(x bigint, k int) returns int return cast(mix32(x, {PLACE * 15485863}L) % k as int)")


def cell_neighbours():
    """UDTF: the neighbours of a cell in an a x b x c cuboid."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="nbr: bigint")
    class CellNeighbours:
        def eval(self, cell: int, a: int, b: int, c: int):
            x, y, z = cell % a, cell // a % b, cell // (a * b)
            for at, top, step in ((x, a, 1), (y, b, a), (z, c, a * b)):
                if at > 0:
                    yield (cell - step,)
                if at < top - 1:
                    yield (cell + step,)

    return CellNeighbours
