"""From queries to questions: two model calls with reflection, a cache of prompts, and tables written after paid calls."""

from __future__ import annotations

import copy
from collections.abc import Callable, Iterator

import pandas as pd
import pyarrow as pa
from pairverify.constants import SYSTEMS
from pairverify.operators import prompts
from pairverify.operators.generators import NoisyGenerator, TextGenerator
from pairverify.plans.querytext import bare_numbers
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def ship() -> None:
    """Let workers get this package's functions with the task."""
    import pairverify
    from pyspark import cloudpickle

    cloudpickle.register_pickle_by_value(pairverify)


def generate(rows: DataFrame, make: Callable[[], TextGenerator], out: str = "question", batch: int = 64) -> DataFrame:
    """Adds the generator's answer to `messages` as column out; one generator for each partition."""
    ship()
    schema = copy.deepcopy(rows.schema).add(out, "string")

    def run(frames):
        model = make()
        for frame in frames:
            said: list[str] = []
            for k in range(0, len(frame), batch):
                said += model.complete([[dict(m.asDict() if hasattr(m, "asDict") else m) for m in ms] for ms in frame["messages"].iloc[k : k + batch]])
            yield frame.assign(**{out: pd.Series(said, index=frame.index, dtype=object)})

    return rows.mapInPandas(run, schema)


def answered(rows: DataFrame, answer: str, then: str | None = None) -> DataFrame:
    """Puts an answer, and on request the next user message, to the end of messages."""
    n = F.size("messages")
    turn = lambda k, role, text: F.struct((n + k).cast("int").alias("turn"), F.lit(role).alias("role"), text.alias("content"))
    more = [turn(1, "assistant", F.col(answer))] + ([turn(2, "user", F.lit(then))] if then else [])
    return rows.withColumn("messages", F.concat("messages", F.array(*more)))


def reflect(rows: DataFrame, make: Callable[[], TextGenerator], draft: str = "draft", out: str = "question") -> DataFrame:
    """A second call that sees the first answer; its answer takes the first one's place."""
    return generate(answered(rows, draft, prompts.REFLECTION_TEXT), make, out)


def both_calls(asked: DataFrame, make: Callable[[], TextGenerator], second: bool, batch: int = 64) -> DataFrame:
    """prompt_sha, draft and question of generate() and then reflect() in one pass, so that messages travel to Python once and not back."""
    ship()
    then = prompts.REFLECTION_TEXT

    def run(frames):
        model = make()
        for frame in frames:
            drafts, last = [], []
            for k in range(0, len(frame), batch):
                own = [[dict(m.asDict() if hasattr(m, "asDict") else m) for m in ms] for ms in frame["messages"].iloc[k : k + batch]]
                said = model.complete(own)
                drafts += said
                if second:
                    turn = lambda ms, j, role, text: {"turn": len(ms) + j, "role": role, "content": text}
                    last += model.complete([[*ms, turn(ms, 1, "assistant", x), turn(ms, 2, "user", then)] for ms, x in zip(own, said, strict=True)])
            yield pd.DataFrame({"prompt_sha": frame["prompt_sha"], "draft": pd.Series(drafts, index=frame.index, dtype=object), "question": pd.Series(last if second else drafts, index=frame.index, dtype=object)})

    return asked.select("prompt_sha", "messages").mapInPandas(run, "prompt_sha string, draft string, question string")


def with_cache(rows: DataFrame, cache: DataFrame) -> DataFrame:
    """The rows whose prompt is not in cache (prompt_sha, question), one for each prompt."""
    return rows.dropDuplicates(["prompt_sha"]).join(cache.select("prompt_sha"), "prompt_sha", "left_anti")


def queries_to_questions(built: DataFrame, make: Callable[[], TextGenerator], reflection: str = "auto", cache: DataFrame | None = None, keep: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """built (from build_prompt) with draft and question.

    reflection: "auto" skips the second call for generators that reason by themselves; "always"; "never". Each prompt is
    asked once. keep writes and rereads a table after each call stage, so that a lost task never asks again.
    """
    asked = built.dropDuplicates(["prompt_sha"]).select("prompt_sha", "messages")
    if cache is not None:
        asked = asked.join(cache.select("prompt_sha"), "prompt_sha", "left_anti")
    second = reflection == "always" or reflection == "auto" and not make().reasons
    if keep:
        drafted = keep(generate(asked, make, "draft"))
        done = keep(reflect(drafted, make)) if second else drafted.withColumn("question", F.col("draft"))
        done = done.select("prompt_sha", "draft", "question")
    else:
        done = both_calls(asked, make, second)
    if cache is not None:
        done = done.unionByName(cache.select("prompt_sha", F.col("question").alias("draft"), "question"))
    return built.join(done, "prompt_sha")


def systems_answers(built: DataFrame, systems=tuple(SYSTEMS), seed: int = 0, revised: bool = True) -> DataFrame:
    """Last (or, if not revised, first) answers of stand-in systems with their truth: adds system, kind, question, correct."""
    ship()
    schema = built.select("query_id", "shape", "q_text", "described").schema.add("system", "string").add("kind", "string").add("question", "string").add("correct", "boolean")

    def run(frames):
        made = {s: NoisyGenerator(s, seed) for s in systems}
        for frame in frames:
            rows = []
            for query_id, shape, q, described in frame[["query_id", "shape", "q_text", "described"]].itertuples(index=False):
                notes = dict(x.split(": ", 1) for x in described if ": " in x)
                for s, g in made.items():
                    kind = g.decide(q, revised)
                    rows.append((query_id, shape, q, list(described), s, kind, g.say(q, kind, notes), kind in ("correct", "alias_from_description", "bad_grammar")))
            yield pd.DataFrame(rows, columns=schema.names)

    return built.select("query_id", "shape", "q_text", "described").mapInPandas(run, schema)


def last_answers(built: DataFrame, systems, seed: int = 0, bare: bool = False) -> DataFrame:
    """built with a column for each stand-in system that holds its last answer; no row moves and no query is joined back.

    bare: also q_bare and, for each system, its name and "_bare": the query and the answer without the numbers of their
    names, as LinearScorer reads them (null where the answer has other names than the query).
    """
    ship()
    systems = tuple(systems)
    names = ["q_bare", *systems, *[f"{s}_bare" for s in systems]]

    @F.arrow_udf(", ".join(f"{x} string" for x in names))
    def run(batches: Iterator[tuple[pa.Array, pa.Array]]) -> Iterator[pa.Array]:
        made = [NoisyGenerator(s, seed) for s in systems]
        for q_text, described in batches:
            rows = []
            for k, q in enumerate(q_text.to_pylist()):
                short, back = bare_numbers(q)
                notes = lambda k=k: dict(x.split(": ", 1) for x in described[k].as_py() if ": " in x)  # noqa: B023, E731
                said = [g.answer(q, short, back, notes) for g in made]
                rows.append([short, *[x[0] for x in said], *[x[1] for x in said]])
            columns = list(zip(*rows, strict=True)) or [()] * len(names)
            yield pa.StructArray.from_arrays([pa.array(x, pa.string()) for x in columns], names=names)

    rows = built.withColumn("_said", run("q_text", "described"))
    return rows.select(*built.columns, *[F.col(f"_said.{x}").alias(x) for x in (names if bare else systems)])


def call_report(built: DataFrame, reasons: bool, negatives: bool = True, price_per_million: float = 0.0) -> DataFrame:
    """Calls, prompt characters, calls saved by asking equal prompts once, and their price."""
    each = 1 + (not reasons) + negatives
    rows = built.agg(F.count("*").alias("queries"), F.count_distinct("prompt_sha").alias("prompts"), F.sum(F.length("prompt")).alias("chars"))
    return rows.select("queries", (F.col("prompts") * each).alias("calls"), ((F.col("queries") - F.col("prompts")) * each).alias("saved"), "chars", (F.col("chars") * each / 4 / 1e6 * price_per_million).alias("price"))
