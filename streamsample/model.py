"""What a sampler is told, what it keeps between batches, and what it reports about a batch."""

from __future__ import annotations

from dataclasses import asdict, dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession

FILLS = ("key", "test", "jump")
SELECTORS = ("pivot", "two_pivot", "combined", "unsorted", "sort", "tail")

STATE_SCHEMA = (
    "stream_id string, version long, threshold double, threshold_id string, n_seen long, w_seen double, held long, k long, k_max long, seed long, method string, weight string, stored long, files array<string>"
)
#: candidates: valid items under the threshold in force; stored: those written, fewer where a first batch is capped in each partition.
REPORT_SCHEMA = (
    "method string, batch_no long, n_items long, w_items double, n_rejected long, candidates long, candidates_max_pe long, stored long, held_before long, held_after long, threshold_before double, "
    "threshold_after double, rounds long, pivots_drawn long, jobs long, rows_moved long, bytes_moved long, rows_examined long, blocks_skipped long, t_insert double, t_select double, t_threshold double, t_gather double"
)


@dataclass(frozen=True)
class SamplerSpec:
    """``id_cols`` name the item; ``weight`` is an SQL expression, None for uniform sampling; the rest has defaults that suit tables.

    fill: ``key`` gives every item its own key (replayable, exact in SQL); ``test`` tests inclusion first and draws the key after; ``jump`` draws how
    much weight, or how many items, to pass over. selector: how the new threshold is found. d: pivots a round. k_max: largest sample allowed
    between two selections; None keeps exactly k. cap: while there is no threshold, a partition writes its k smallest only. incremental: candidates are
    spread over the partitions as they come in, and the combined selector moves no others. variate: a column with the items' variates, where they were drawn before.
    """

    stream_id: str
    id_cols: tuple[str, ...]
    weight: str | None
    k: int
    k_max: int | None = None
    seed: int = 7
    fill: str = "key"
    selector: str = "tail"
    d: int = 8
    block: int = 32
    lazy: bool = True
    deep: bool = False
    finish: int = 256
    gather_bytes: int = 64 << 20
    cap: bool = True
    incremental: bool = False
    variate: str | None = None

    def __post_init__(self) -> None:
        if self.k < 1 or (self.k_max is not None and self.k_max < self.k):
            raise ValueError("1 <= k <= k_max is needed")
        if self.fill not in FILLS or self.selector not in SELECTORS:
            raise ValueError(f"fill is one of {FILLS}, selector one of {SELECTORS}")
        if self.variate and (self.deep or self.fill != "key"):
            raise ValueError("variates drawn before serve plain keys only")

    def but(self, **changes) -> SamplerSpec:
        return replace(self, **changes)


@dataclass
class State:
    """One row between batches. ``threshold`` is None until more than k items were seen."""

    threshold: float | None = None
    threshold_id: str | None = None
    version: int = -1
    n_seen: int = 0
    w_seen: float = 0.0
    held: int = 0


@dataclass
class Report:
    method: str
    batch_no: int
    n_items: int = 0
    w_items: float = 0.0
    n_rejected: int = 0
    candidates: int = 0
    candidates_max_pe: int = 0
    stored: int = 0
    held_before: int = 0
    held_after: int = 0
    threshold_before: float | None = None
    threshold_after: float | None = None
    rounds: int = 0
    pivots_drawn: int = 0
    jobs: int = 0
    rows_moved: int = 0
    bytes_moved: int = 0
    rows_examined: int = 0
    blocks_skipped: int = 0
    t_insert: float = 0.0
    t_select: float = 0.0
    t_threshold: float = 0.0
    t_gather: float = 0.0


@dataclass
class Reports:
    rows: list[Report] = field(default_factory=list)

    def table(self, spark: SparkSession) -> DataFrame:
        names = [c.split()[0] for c in REPORT_SCHEMA.split(", ")]
        return spark.createDataFrame([tuple(asdict(r)[n] for n in names) for r in self.rows], REPORT_SCHEMA)
