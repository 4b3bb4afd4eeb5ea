"""Prompts with four parts, replies, the indexed taxonomy, and the words they take."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.io import REPLY


@dataclass(frozen=True)
class Template:
    """Role, task, reply example and requirements; ``{platform}`` and ``{language}`` are filled in."""

    role: str = "You know {platform} and write {language} for it."
    task: str = "Say what the script does as a whole, then list its steps in order."
    reply_example: str = '{{"overall": "...", "steps": [{{"pos": 1, "name": "...", "description": "..."}}]}}'
    requirements: str = "Answer with JSON only. Name each step in at most ten words."
    platform: str = "a map platform"
    language: str = "JavaScript"

    def text(self) -> str:
        parts = (("Role", self.role), ("Task", self.task), ("Reply example", self.reply_example), ("Requirements", self.requirements))
        return "\n".join(f"{name}: {part.format(platform=self.platform, language=self.language)}" for name, part in parts)


def build_extract_prompt(scripts: DataFrame, template: Template = Template(), key: str = "script_id", text: str = "text") -> DataFrame:  # noqa: B008
    """script_id, prompt: the template's text is one literal for all scripts."""
    return scripts.select(F.col(key).alias("script_id"), F.concat(F.lit(template.text() + "\nScript:\n"), F.coalesce(F.col(text), F.lit(""))).alias("prompt"))


def parse_reply(replies: DataFrame, key: str = "script_id", reply: str = "reply") -> tuple[DataFrame, DataFrame]:
    """Steps (script_id, overall, pos, name, description) and the replies that are no such JSON (script_id, reply)."""
    read = replies.select(key, reply, F.from_json(reply, REPLY, {"mode": "PERMISSIVE", "columnNameOfCorruptRecord": "_corrupt_record"}).alias("r"))
    broken = F.col("r").isNull() | F.col("r._corrupt_record").isNotNull() | F.col("r.steps").isNull()
    steps = read.where(~broken).select(F.col(key).alias("script_id"), "r.overall", F.inline("r.steps"))
    return steps, read.where(broken).select(F.col(key).alias("script_id"), reply)


def index_taxonomy(taxonomy: DataFrame) -> DataFrame:
    """One row: the framework as a compact indexed text, every name once. The taxonomy is model-sized."""
    groups = taxonomy.groupBy("l1", "l2").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("l3_id", "l3"))), lambda x: F.concat(x["l3_id"].cast("string"), F.lit(":"), x["l3"])), ", ").alias("f"))
    stages = groups.groupBy("l1").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("l2", "f"))), lambda x: F.concat(x["l2"], F.lit(" ("), x["f"], F.lit(")"))), "; ").alias("g"))
    lines = F.transform(F.array_sort(F.collect_list(F.struct("l1", "g"))), lambda x: F.concat(x["l1"], F.lit(": "), x["g"]))
    return stages.agg(F.array_join(lines, "\n").alias("index_text"))


def _words(col: Column) -> Column:
    return F.size(F.filter(F.split(col, r"[ \n]+"), lambda x: x != "")).cast("long")


def token_volume(taxonomy: DataFrame) -> DataFrame:
    """Words of the indexed text and of the full paths written out, one row."""
    full = taxonomy.agg(F.sum(_words(F.concat_ws(" ", "l1", "l2", "l3"))).alias("full_words")).withColumn("_k", F.lit(1))
    short = index_taxonomy(taxonomy).select(_words(F.col("index_text")).alias("index_words"), F.lit(1).alias("_k"))
    return short.join(full, "_k").select("index_words", "full_words")


def build_map_prompt(queue: DataFrame, taxonomy: DataFrame) -> DataFrame:
    """batch, prompt: the indexed taxonomy once and the batch's combinations in queue order."""
    ordered = F.transform(F.array_sort(F.collect_list(F.struct("place", "items"))), lambda x: F.concat(x["place"].cast("string"), F.lit(". "), F.array_join(x["items"], " + ")))
    batches = queue.groupBy("batch").agg(F.array_join(ordered, "\n").alias("combos")).withColumn("_k", F.lit(1))
    text = index_taxonomy(taxonomy).withColumn("_k", F.lit(1))
    return batches.join(F.broadcast(text), "_k").select("batch", F.concat(F.lit("Functions:\n"), "index_text", F.lit("\nCombinations:\n"), "combos", F.lit("\nAnswer with one function index a line.")).alias("prompt"))
