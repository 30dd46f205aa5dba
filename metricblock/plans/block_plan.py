"""The method's own plan: which strategy each step takes, and why, beside Spark's physical plan."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from metricblock.operators import knn, landmarks, mds


@dataclass(frozen=True)
class Step:
    name: str
    how: str
    cost: str


@dataclass(frozen=True)
class BlockPlan:
    """Key, embed, index, search, pair, filter: one step each."""

    steps: tuple[Step, ...]

    def text(self) -> str:
        width = max(len(s.name) for s in self.steps)
        return "\n".join(f"{s.name.ljust(width)}  {s.how}  [{s.cost}]" for s in self.steps)


def plan_blocks(distinct: int, K: int = 7, L: int = 300, B: int = 50, embedding: str = "landmark", pairs: str = "star", theta: float = 2) -> BlockPlan:
    """What ``dedup`` or ``ReferenceIndex.fit`` will choose for that many distinct values."""
    exact = L <= landmarks.EXACT_LANDMARKS and distinct <= landmarks.EXACT_ROWS
    size = knn.tree_bytes(distinct, K)
    broadcast = size <= knn.BROADCAST_BYTES
    if embedding == "complete" and distinct > mds.DISTRIBUTED_ROWS:
        raise ValueError(f"the complete embedding is refused above {mds.DISTRIBUTED_ROWS} values: use landmarks")
    embed = (
        Step("embed", "complete, " + ("on the driver" if distinct <= mds.DRIVER_ROWS else "in blocks of rows"), f"{distinct * (distinct - 1) // 2} distances")
        if embedding == "complete"
        else Step("embed", f"{L} landmarks, " + ("farthest first" if exact else "farthest first by coreset"), f"{L * (L - 1) // 2 + L * max(0, distinct - L)} distances")
    )
    per_block = B if pairs == "star" else B * (B + 1) // 2
    return BlockPlan(
        (
            Step("key", "distinct values by hash", "one exchange, partial sums first"),
            embed,
            Step("index", "one kd-tree, shipped" if broadcast else f"{-(-distinct // knn.CELL_POINTS)} cells, two rounds", f"{size} bytes"),
            Step("search", f"{B} neighbours each", "no exchange" if broadcast else "queries move, cells stay"),
            Step("pair", pairs, f"at most {per_block * distinct} pairs before distinct"),
            Step("filter", f"edit distance at most {theta:g}", "two equi-joins"),
        )
    )


def explain_blocks(plan: BlockPlan, df: DataFrame | None = None) -> str:
    """The method plan, and Spark's plan of ``df`` below it."""
    out = "== Method plan ==\n" + plan.text()
    return out if df is None else f"{out}\n{df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString('formatted'))}"
