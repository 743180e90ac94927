"""Answers that come from outside: stored ones, and a model called once a batch of prompts."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame


def stored_answers(prompts: DataFrame, answers: DataFrame, key: str, model: str) -> DataFrame:
    """prompts with each stored answer to them; a prompt without one keeps a row of nulls, so that it counts as unanswered."""
    return prompts.join(answers.where(answers["model"] == model), key, "left")


def batch_answers(prompts: DataFrame, call: Callable[[list[str | None]], list[str | None]], key: str, prompt: str = "prompt", size: int = 64) -> DataFrame:
    """key, answer: call gets at most ``size`` prompts at a time and gives as many answers, in their order.
    key and prompt alone go to Python. A task that is run again calls again, so call should be repeatable or store what it answered."""
    kind = dict(prompts.dtypes)[key]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, size):
                part = batch.slice(at, size)
                got = call(part.column(1).to_pylist())
                if len(got) != part.num_rows:
                    raise ValueError(f"{part.num_rows} prompts, {len(got)} answers")
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(got, pa.string())], ["key", "answer"])

    return prompts.select(key, prompt).mapInArrow(run, f"key {kind}, answer string").withColumnRenamed("key", key)
