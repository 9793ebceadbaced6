"""Extension: scoring streams with published weights, and learning from them batch by batch."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.optim import GradientDescent, Optimizer
from ..operators import assemble, classify, gradients, params
from ..plans.storage import stored


def score_batch(versions: params.Versions, to_entries: Callable[[DataFrame], DataFrame], sink: Callable[[DataFrame, int], None], threshold: float = 0.5):
    """For ``foreachBatch``: scores a micro-batch of whole samples with the version current at its start."""

    def run(batch: DataFrame, batch_id: int) -> None:
        sink(classify.predict(versions.load(), to_entries(batch), threshold=threshold), batch_id)

    return run


def learn_batch(versions: params.Versions, to_entries: Callable[[DataFrame], DataFrame], optimizer: Optimizer | None = None, alpha: float = 0.0):
    """For ``foreachBatch``: one gradient step on each micro-batch, published under the batch's number.

    A batch that is run again after a failure finds its version published and does nothing.
    """
    optimizer = optimizer or GradientDescent(alpha)

    def run(batch: DataFrame, batch_id: int) -> None:
        now = versions.current()
        if now is not None and now >= batch_id + 1:
            return
        entries = stored(to_entries(batch).where("label is not null"))
        fresh = params.init(entries)
        theta = fresh if now is None else versions.load(now).unionByName(fresh.join(versions.load(now), "f", "left_anti"))
        held = assemble.margins(assemble.distribute(theta, entries))
        grads = gradients.from_residuals(gradients.residuals(held), entries)
        versions.publish(params.update(theta, grads, optimizer, batch_id + 1).select("f", "theta"), batch_id + 1)

    return run


def deduplicated(samples: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Samples of a stream once each, by id, within the watermark; of a table, once each."""
    if samples.isStreaming:
        return samples.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["sample_id"])
    return samples.dropDuplicates(["sample_id"])


def running_counts(events: DataFrame, key: str = "user_id") -> DataFrame:
    """Events seen of each key so far, by arbitrary state that grows with the keys alone."""
    from collections.abc import Iterator

    import pandas as pd
    from pyspark.sql.streaming.state import GroupState

    def step(k, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n = (state.get[0] if state.exists else 0) + sum(len(f) for f in frames)
        state.update((n,))
        yield pd.DataFrame({"key": [k[0]], "n": [n]})

    kind = events.schema[key].dataType.simpleString()
    return events.select(F.col(key)).groupBy(key).applyInPandasWithState(step, f"key {kind}, n bigint", "n bigint", "update", "NoTimeout")
