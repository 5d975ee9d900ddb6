"""Messages between feature nodes and coordinator, counted from their shapes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMA = "run string, phase int, k int, src string, dst string, kind string, doubles long, bytes long"


class Ledger:
    """Rows of doubles sent; one double is eight bytes."""

    def __init__(self, run: str, nodes: int):
        self.run, self.nodes, self.rows = run, nodes, []

    def send(self, phase: int, k: int, src: str, dst: str, kind: str, doubles: int) -> None:
        self.rows.append((self.run, phase, k, src, dst, kind, int(doubles), int(doubles) * 8))

    def eager(self, phase: int, k: int, n: int, d: int) -> None:
        """Every node ships its atom and score; the winner and its step go back to all."""
        for c in range(self.nodes):
            self.send(phase, k, f"node{c}", "coordinator", "atom", n + d + 2)
            self.send(phase, k, "coordinator", f"node{c}", "update", n + d + 3)

    def lazy(self, phase: int, k: int, n: int, d: int, winner: int) -> None:
        """Scores first; the winner alone ships its atom."""
        for c in range(self.nodes):
            self.send(phase, k, f"node{c}", "coordinator", "score", 1)
        self.send(phase, k, f"node{winner}", "coordinator", "atom", n + d + 1)
        for c in range(self.nodes):
            self.send(phase, k, "coordinator", f"node{c}", "update", n + d + 3)

    def flush(self, phase: int, k: int, n: int, d: int) -> None:
        """The last step's update, without which node coefficients would lag one step behind."""
        for c in range(self.nodes):
            self.send(phase, k, "coordinator", f"node{c}", "flush", n + d + 3)

    def total(self) -> int:
        return sum(r[-1] for r in self.rows)

    def rounds(self) -> int:
        """Round trips: two a step where scores travel ahead of the atom, else one."""
        kinds: dict[tuple[int, int], set[str]] = {}
        for r in self.rows:
            kinds.setdefault((r[1], r[2]), set()).add(r[5])
        return sum(2 if "score" in s else 1 for s in kinds.values() if s != {"flush"})

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, SCHEMA)


def summary(ledger: DataFrame) -> DataFrame:
    """Bytes and messages by phase and kind, with subtotals."""
    return ledger.rollup("phase", "kind").agg(F.sum("bytes").alias("bytes"), F.count("*").alias("messages"))
