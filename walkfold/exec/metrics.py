"""What a run costs: edges processed and vertices changed by step, shuffled records, seconds, data sizes."""

from __future__ import annotations

from dataclasses import dataclass, field


@dataclass
class RunMetrics:
    """``count_records``: also read how many rows each step shuffled (after partial aggregation) from its finished plan."""

    steps: list[dict] = field(default_factory=list)
    vertex_bytes: int = 0
    edge_bytes: int = 0
    count_records: bool = False

    def add(self, edges: int, changed: int, seconds: float, model: str, records: int = 0) -> None:
        self.steps.append({"step": len(self.steps) + 1, "edges": edges, "changed": changed, "seconds": seconds, "model": model, "records": records})

    @property
    def edges_processed(self) -> int:
        return sum(s["edges"] for s in self.steps)

    @property
    def n_steps(self) -> int:
        return len(self.steps)

    @property
    def records_per_edge(self) -> float:
        """Shuffled records per processed edge, after partial sums: what atomic updates are in shared memory."""
        return sum(s["records"] for s in self.steps) / max(1, self.edges_processed)


def edge_work_ratio(a: RunMetrics, b: RunMetrics) -> float:
    return a.edges_processed / max(1, b.edges_processed)
