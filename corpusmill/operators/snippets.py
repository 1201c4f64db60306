"""Synthesis with verification: seeds, prompts, a pluggable generator, tests run in processes of their own, and what passes is kept.

A generator is any function from prompts to (code, test) pairs; `stub_generator` is a deterministic one without a model, so that the whole chain runs
offline. Runners are a registry by language: a language without one gives the verdict "skipped" and is not kept. Each run has limits of time, memory and
output, an empty environment and a folder of its own; it isolates mistakes, not malice, so untrusted models need a sandbox around the executors.
"""

from __future__ import annotations

import resource
import subprocess
import sys
import tempfile
from collections.abc import Callable, Iterator
from pathlib import Path

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from corpusmill.plans.durable import settled

#: Tasks over which programs are dealt.
PROCESSES = 256

Generator = Callable[[pd.Series], pd.DataFrame]


def stub_generator(prompts: pd.Series) -> pd.DataFrame:
    """Code that counts the prompt's words, with a test; every third prompt by length gets a test that fails."""
    counts = prompts.fillna("").map(lambda p: len(p.split()))
    code = counts.map(lambda n: f"def words(text):\n    return len(text.split())  # {n}\n")
    test = pd.Series([f"assert words({' '.join(['w'] * min(n, 50))!r}) == {min(n, 50) + (n % 3 == 0)}\n" for n in counts], index=prompts.index, dtype=object)
    return pd.DataFrame({"code": code, "test": test})


def generate(prompts: DataFrame, generator: Generator = stub_generator) -> DataFrame:
    """prompts (id, lang, prompt) with code and test."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            made = generator(batch["prompt"])
            yield batch.assign(code=made["code"].to_numpy(), test=made["test"].to_numpy())

    return prompts.select("id", "lang", "prompt").mapInPandas(run, "id long, lang string, prompt string, code string, test string")


def run_python(code: str, test: str, seconds: float, megabytes: int) -> str:
    def limits() -> None:
        resource.setrlimit(resource.RLIMIT_AS, (megabytes << 20, megabytes << 20))
        resource.setrlimit(resource.RLIMIT_CPU, (int(seconds) + 1, int(seconds) + 1))
        resource.setrlimit(resource.RLIMIT_FSIZE, (1 << 20, 1 << 20))

    with tempfile.TemporaryDirectory() as own:  # a scratch folder of one run; nothing in it is read elsewhere
        path = Path(own, "snippet.py")
        path.write_text(f"{code}\n{test}\n")
        try:
            done = subprocess.run([sys.executable, "-I", "-S", str(path)], cwd=own, env={}, stdin=subprocess.DEVNULL, stdout=subprocess.DEVNULL, stderr=subprocess.PIPE, timeout=seconds, preexec_fn=limits)  # noqa: PLW1509
        except subprocess.TimeoutExpired:
            return "timeout"
    if done.returncode == 0:
        return "passed"
    last = done.stderr.decode("utf-8", "replace").strip().rsplit("\n", 1)[-1]
    return "failed" if last.startswith("AssertionError") else "invalid" if last.startswith(("SyntaxError", "IndentationError")) else "memory" if last.startswith("MemoryError") else "raised"


RUNNERS: dict[str, Callable[[str, str, float, int], str]] = {"python": run_python}


def run_tests(snippets: DataFrame, seconds: float = 5.0, megabytes: int = 512, runners: dict[str, Callable] | None = None) -> DataFrame:
    """snippets (id, lang, code, test, ...) with a verdict; null code or test is invalid.

    Snippets of the same language, code and test are one program, which runs once. The programs are settled first, so a generator is not asked twice.
    """
    known = RUNNERS if runners is None else runners
    columns = snippets.columns

    def verdict(lang: str | None, code: str | None, test: str | None) -> str:
        if lang not in known:
            return "skipped"
        return known[lang](code, test, seconds, megabytes) if code and test else "invalid"

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            yield batch.assign(verdict=[verdict(*x) for x in zip(batch["lang"], batch["code"], batch["test"])])

    program = F.sha2(F.to_json(F.struct("lang", "code", "test")), 256)  # nulls are left out, so no value stands for one
    held = settled(snippets.withColumn("__program", program))
    # each program takes a process of its own, so they are dealt out evenly however small their texts are
    programs = held.select("__program", "lang", "code", "test").dropDuplicates(["__program"]).repartition(PROCESSES, "__program")
    verdicts = settled(programs.mapInPandas(run, "__program string, lang string, code string, test string, verdict string").select("__program", "verdict"))
    return held.join(verdicts, "__program").select(*columns, "verdict")


def keep_passing(snippets: DataFrame, **limits) -> DataFrame:
    return run_tests(snippets, **limits).where("verdict = 'passed'")


def keyword_subset(files: DataFrame, keywords: tuple[str, ...], share: float = 1.0) -> DataFrame:
    """Files whose text holds one of the keywords in any case, and of those a share by the hash of the id."""
    from corpusmill.operators.sampling import P31, unit_hash

    low = F.lower("text")
    hit: Column = F.lit(False)
    for k in keywords:
        hit = hit | low.contains(k.lower())
    return files.where(hit).where(unit_hash(F.col("file_id")) < int(share * P31))


def useful_sentences(rows: DataFrame, best: int = 5, least: int = 6, most: int = 60) -> DataFrame:
    """(id, rank, sentence): of each row's text the sentences of least..most words with the most different words."""
    cut = F.explode(F.array_distinct(F.filter(F.transform(F.split("text", r"[.!?]+\s+"), lambda x: F.trim(x)), lambda x: x != ""))).alias("sentence")
    words = F.filter(F.split(F.lower("sentence"), r"\s+"), lambda x: x != "")
    sized = rows.select("id", cut).withColumns({"n": F.size(words), "d": F.size(F.array_distinct(words))}).where(F.col("n").between(least, most))
    rank = F.row_number().over(Window.partitionBy("id").orderBy(F.desc("d"), "sentence"))
    return sized.select("id", rank.alias("rank"), "sentence").where(F.col("rank") <= best)
