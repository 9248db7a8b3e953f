"""Relations of the engine and the parameters of a run."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import types as T


def _relation(**fields: T.DataType) -> T.StructType:
    return T.StructType([T.StructField(n, t, False) for n, t in fields.items()])


LONG, INT, DOUBLE, TEXT = T.LongType(), T.IntegerType(), T.DoubleType(), T.StringType()
EDGE = _relation(qid=LONG, vid=LONG)
HYPEREDGE = _relation(qid=LONG, members=T.ArrayType(LONG, False))
ASSIGN = _relation(vid=LONG, bucket=INT)
SHARE = _relation(qid=LONG, bucket=INT, cnt=LONG)
GAIN = _relation(vid=LONG, src=INT, dst=INT, gain_fx=LONG)
EXCHANGE = _relation(src=INT, dst=INT, gbin=INT, candidates=LONG, gain_sum=LONG, admitted=LONG, threshold=LONG)
PROGRESS = _relation(level=INT, iter=INT, moved=LONG, moved_frac=DOUBLE, fanout=DOUBLE, pfanout=DOUBLE, shuffle_rows=LONG)
RESULT = _relation(graph=TEXT, method=TEXT, k=INT, p=DOUBLE, eps=DOUBLE, fanout=DOUBLE, imbalance=DOUBLE, run_s=DOUBLE, status=TEXT)


@dataclass(frozen=True)
class PartitionSpec:
    """Parameters of a partitioning run.

    objective: 'pfanout' (needs 0 < p < 1), 'fanout' (p = 1) or 'clique' (the limit p -> 0).
    exchange: 'plain' (coin per ordered pair), 'ranked' (exact pairing by gain) or 'histogram' (by gain bins).
    arity: children per split; None goes straight to k buckets. iterations: per level; None is 60 for
    direct runs and 20 per split. slack: histogram runs may also use the imbalance allowance. reuse: share of moved
    vertices up to which the next turn updates shares and gains instead of counting them anew (same result). coins: 'portable'
    (md5, the same in other engines) or 'fast' (the engine's own hash).
    """

    k: int = 2
    eps: float = 0.05
    p: float = 0.5
    arity: int | None = None
    iterations: int | None = None
    tol: float = 0.0
    seed: int = 42
    objective: str = "pfanout"
    exchange: str = "plain"
    nonpositive: bool = False
    slack: bool = False
    lookahead: bool = False
    init: str = "random"
    damp: float = 1.0
    penalty: float = 0.0
    repair: bool = True
    keep_best: bool = True
    prune: bool = True
    reuse: float = 0.01
    coins: str = "portable"

    def __post_init__(self):
        if self.k < 2:
            raise ValueError("k must be at least 2")
        if self.eps < 0:
            raise ValueError("eps must not be negative")
        if not 0 < self.p <= 1:
            raise ValueError("p must be in (0, 1]")
        if self.objective not in ("pfanout", "fanout", "clique"):
            raise ValueError(f"unknown objective {self.objective}")
        if self.exchange not in ("plain", "ranked", "histogram"):
            raise ValueError(f"unknown exchange {self.exchange}")
        if self.arity is not None and self.arity < 2:
            raise ValueError("arity must be at least 2")
        if self.coins not in ("portable", "fast"):
            raise ValueError(f"unknown coins {self.coins}")
        if not 0 <= self.damp <= 1:
            raise ValueError("damp must be in [0, 1]")
        if self.objective == "pfanout" and self.p == 1:
            object.__setattr__(self, "objective", "fanout")

    def but(self, **changes) -> PartitionSpec:
        return replace(self, **changes)

    @property
    def rounds(self) -> int:
        return self.iterations if self.iterations is not None else (60 if self.arity is None else 20)


@dataclass
class PartitionResult:
    """assign: (vid, bucket); progress: one row per iteration; spec: what was asked for."""

    assign: DataFrame
    progress: list[dict]
    spec: PartitionSpec

    def progress_frame(self) -> DataFrame:
        rows = [tuple(r[f.name] for f in PROGRESS.fields) for r in self.progress]
        return self.assign.sparkSession.createDataFrame(rows, PROGRESS)
