"""An operator graph: operators carry the contract under which their function may run in parallel; the optimizer is Spark's.

Contracts are held against the plan that a function builds: a function of single records may only project, filter and explode;
one of groups may only put records of a key together, so what it groups or windows by must hold the keys; one of pairs joins.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from enum import Enum

from pyspark.sql import Column, DataFrame

from netan.storage import bucketed, written


class Contract(Enum):
    RECORD = "each record alone"
    GROUP = "all records of a key"
    PAIR = "each matching pair of records"


class BrokenContract(ValueError):
    """A function does what its operator's contract rules out."""


@dataclass
class Node:
    contract: Contract
    inputs: list["Node"]
    build: Callable[..., DataFrame]
    keys: tuple[str, ...] = ()
    kept: tuple[str, ...] = field(default=())

    def keeps(self, *columns: str) -> "Node":
        """Output contract: the result is dealt by these columns. `Plan.stored` writes it so, and what groups or joins it by them
        later needs no exchange."""
        self.kept = columns
        return self


def _above(df: DataFrame, inputs: list[DataFrame]) -> list:
    """The nodes of df's analysed plan that are not part of its inputs."""
    ends = [x._jdf.queryExecution().analyzed() for x in inputs]
    found, open_ = [], [df._jdf.queryExecution().analyzed()]
    while open_:
        plan = open_.pop()
        if any(plan.sameResult(x) for x in ends):
            continue
        found.append(plan)
        children = plan.children()
        open_ += [children.apply(k) for k in range(children.size())]
    return found


def _names(expressions) -> set[str]:
    return {expressions.apply(k).toString().split("#")[0].strip("'") for k in range(expressions.size())}


def check(node: Node, df: DataFrame, inputs: list[DataFrame]) -> None:
    """Raises BrokenContract if what the node's function has built is not what its contract allows."""
    allowed = {"Project", "Filter", "Generate", "SubqueryAlias"}
    allowed |= {Contract.RECORD: {"Union"}, Contract.GROUP: {"Aggregate", "Window"}, Contract.PAIR: {"Join"}}[node.contract]
    for plan in _above(df, inputs):
        name = plan.nodeName()
        if name not in allowed:
            raise BrokenContract(f"{name} in an operator of {node.contract.value}")
        if name in ("Aggregate", "Window"):
            by = _names(plan.groupingExpressions() if name == "Aggregate" else plan.partitionSpec())
            if not set(node.keys) <= by:
                raise BrokenContract(f"{name} by {sorted(by)} in an operator of groups by {sorted(node.keys)}")


class Plan:
    """Operators as nodes; `result` puts the DataFrame together and lets Spark optimise it as a whole."""

    @staticmethod
    def source(df: DataFrame) -> Node:
        return Node(Contract.RECORD, [], lambda: df)

    @staticmethod
    def map(node: Node, *columns: Column | str, where: Column | None = None) -> Node:
        return Node(Contract.RECORD, [node], lambda df: (df if where is None else df.where(where)).select(*columns))

    @staticmethod
    def join(left: Node, right: Node, on: list[str] | str, how: str = "inner") -> Node:
        return Node(Contract.PAIR, [left, right], lambda a, b: a.join(b, on, how), (on,) if isinstance(on, str) else tuple(on))

    @staticmethod
    def group(node: Node, keys: list[str], *aggregates: Column) -> Node:
        return Node(Contract.GROUP, [node], lambda df: df.groupBy(*keys).agg(*aggregates), tuple(keys))

    @staticmethod
    def reduce(node: Node, keys: list[str], function: Callable[[DataFrame], DataFrame]) -> Node:
        return Node(Contract.GROUP, [node], function, tuple(keys))

    @staticmethod
    def union(left: Node, right: Node) -> Node:
        return Node(Contract.RECORD, [left, right], lambda a, b: a.unionByName(b))

    @staticmethod
    def result(node: Node, checked: bool = False) -> DataFrame:
        """checked: every operator's contract is held against the plan."""
        inputs = [Plan.result(x, checked) for x in node.inputs]
        out = node.build(*inputs)
        if checked and inputs:
            check(node, out, inputs)
        return out

    @staticmethod
    def stored(node: Node, name: str = "stored", checked: bool = False) -> DataFrame:
        """The result as a table, in buckets by the column it is said to keep."""
        out = Plan.result(node, checked)
        if not node.kept:
            return written(out, name)
        parts = int(out.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        return bucketed(out.repartition(parts, *node.kept), name, node.kept[0], parts)
