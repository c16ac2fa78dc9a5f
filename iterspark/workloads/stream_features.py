"""Stream features: windowed features of `events`, replayed as a file stream."""

from __future__ import annotations

from iterspark.streaming.minibatch import StreamRunner, replayed, tumbling_counts


def stream_features(spark, source: str, root: str, parts: int = 4) -> StreamRunner:
    """Runs all batches; the kept steps and the decision are under `root`."""
    steps = [("batch", [], lambda b: b), ("typed", ["batch"], lambda b: b.filter("value is not null")), ("features", ["typed"], lambda t: tumbling_counts(t))]
    runner = StreamRunner(spark, f"{root}/state", steps, ["features"])
    runner.start(replayed(spark, source, f"{root}/input", parts), f"{root}/checkpoint").awaitTermination()
    return runner
