"""Log-probabilities from outside: a model that a function loads once a worker scores Arrow batches of pairs."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

#: (prompts, responses) -> (log-probabilities in nats, numbers of tokens); null marks what can't be scored.
Scorer = Callable[[list, list], tuple[list, list]]


def with_scorer(pairs: DataFrame, load: Callable[[], Scorer], model: str = "ref", rows: int = 256) -> DataFrame:
    """(pair_id, {model}_w, {model}_l, n_w, n_l): both responses' log-probabilities in whole micro-nats.

    ``load`` runs once in each task, before its first row, so that a model is never sent from the driver; the scorer
    gets ``rows`` pairs at a time, so that its memory doesn't grow with the partition.  Null prompts and responses are
    passed as empty strings.  A scorer that returns another number of values than it was given is an error.
    """

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        score = None
        for whole in batches:
            for at in range(0, whole.num_rows, rows):
                batch = whole.slice(at, rows)
                score = score or load()
                text = lambda c: [x or "" for x in batch[c].to_pylist()]  # noqa: B023, E731
                columns = [batch["pair_id"]]
                counts = []
                for side in ("chosen", "rejected"):
                    lp, n = score(text("prompt"), text(side))
                    if len(lp) != batch.num_rows or len(n) != batch.num_rows:
                        raise ValueError(f"the scorer returned {len(lp)} and {len(n)} values for {batch.num_rows} pairs")
                    columns.append(pa.array([None if x is None or x != x or abs(x) == float("inf") else int((x * 1_000_000 + 0.5) // 1) for x in lp], pa.int64()))
                    counts.append(pa.array(n, pa.int32()))
                yield pa.RecordBatch.from_arrays(columns + counts, ["pair_id", f"{model}_w", f"{model}_l", "n_w", "n_l"])

    return pairs.select("pair_id", "prompt", "chosen", "rejected").mapInArrow(work, f"pair_id long, {model}_w long, {model}_l long, n_w int, n_l int")
