"""Prompting of language models as detectors. Wording is ours: the published templates are not available."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.text import parse_verdict

SYSTEM = "You review code for security flaws."
ASK = {"direct": "Is this function flawed? Answer YES or NO.", "reason": "Think step by step about inputs, bounds and lifetimes, then end with YES or NO: is this function flawed?"}


def _message(role: str, content: Column) -> Column:
    return F.struct(F.lit(role).alias("role"), content.alias("content"))


def question(text: Column, style: str) -> Column:
    return F.concat(text, F.lit("\n\n" + ASK[style]))


def pick_shots(train: DataFrame, text: str = "text") -> DataFrame:
    """One row: shot_flawed and shot_benign, the first of each label by id."""
    return train.agg(F.min_by(text, F.when(F.col("label") == 1, F.col("sample_id"))).alias("shot_flawed"), F.min_by(text, F.when(F.col("label") == 0, F.col("sample_id"))).alias("shot_benign"))


def build_prompts(df: DataFrame, shots: DataFrame, style: str = "direct", text: str = "text") -> DataFrame:
    """df with messages: system, two answered examples (one of each label), then the question."""
    rows = df.crossJoin(F.broadcast(shots))
    messages = F.array(
        _message("system", F.lit(SYSTEM)),
        _message("user", question(F.col("shot_flawed"), style)), _message("assistant", F.lit("YES")),
        _message("user", question(F.col("shot_benign"), style)), _message("assistant", F.lit("NO")),
        _message("user", question(F.col(text), style)),
    )
    return rows.withColumn("style", F.lit(style)).withColumn("messages", messages).drop("shot_flawed", "shot_benign")


def render(messages: Column) -> Column:
    return F.array_join(F.transform(messages, lambda m: F.concat(m["role"], F.lit(": "), m["content"])), "\n")


def finetune_export(samples: DataFrame, text: str = "text") -> DataFrame:
    """record: one chat example a sample, as JSON."""
    answer = F.when(F.col("label") == 1, "YES").otherwise("NO")
    messages = F.array(_message("system", F.lit(SYSTEM)), _message("user", question(F.col(text), "direct")), _message("assistant", answer))
    return samples.select("sample_id", F.to_json(F.struct(messages.alias("messages"))).alias("record"))


def score_with(df: DataFrame, responder: Callable[[list[str]], list[str]], done: DataFrame | None = None) -> DataFrame:
    """sample_id, completion, verdict. ``responder`` maps a batch of rendered prompts to answers (greedy decoding is its
    affair); ids in ``done`` are skipped, so a run resumes from what was written."""
    todo = df if done is None else df.join(done.select("sample_id"), "sample_id", "left_anti")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            yield pd.DataFrame({"sample_id": batch["sample_id"], "completion": responder(batch["prompt"].tolist())})

    answers = todo.select("sample_id", render(F.col("messages")).alias("prompt")).mapInPandas(run, "sample_id string, completion string")
    return answers.withColumn("verdict", parse_verdict(F.col("completion")))


def stub_responder(prompts: list[str]) -> list[str]:
    """A deterministic stand-in for a service: answers by a digest of the prompt."""
    import hashlib

    answers = ("YES", "NO", "The function looks fine. NO", "It is vulnerable: YES", "unclear")
    return [answers[hashlib.md5(p.encode()).digest()[0] % len(answers)] for p in prompts]
