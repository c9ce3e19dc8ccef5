"""Alignment data: prompts, conversation checks, templates, personal data, lexical diversity."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import text as T
from ..functions.text import md5_int

PERSONAL = {
    "EMAIL": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+",
    "IP": r"\b\d{1,3}(?:\.\d{1,3}){3}\b",
    "PHONE": r"\+\d[\d ().-]{7,}\d",
    "KEY": r"\b(?:AKIA[0-9A-Z]{16,}|[0-9a-f]{32,})\b",
}
#: Openers that an assistant, not a user, would write, and prompts that talk about the assistant instead of asking.
OPENER = r"(?i)^\s*(?:sure|certainly|of course|great question|as an ai[^,.!]*)[,.!:]\s*"
SECOND_HAND = r"(?i)^\s*(?:ask|tell|request) (?:the|your) assistant\b"
#: A refusal by its first words.
REFUSAL = r"(?i)^\s*(?:i can(?:'|no)t|i cannot|i won't|i am not able to|sorry)\b"
#: Cut of the type-token factor measure.
MTLD_CUT = 0.72


def first_prompts(conv: DataFrame) -> DataFrame:
    """conv_id, prompt: the first user turn."""
    return conv.filter("role = 'user'").groupBy("conv_id").agg(F.min_by("text", "turn").alias("prompt"))


def redact(text: Column) -> Column:
    for name, pattern in PERSONAL.items():
        text = F.regexp_replace(text, pattern, f"<{name}>")
    return text


def find_personal(text: Column) -> dict[str, Column]:
    """Findings of each kind."""
    return {name: F.size(F.regexp_extract_all(text, F.lit(pattern), F.lit(0))) for name, pattern in PERSONAL.items()}


def clean_generated(conv: DataFrame) -> DataFrame:
    """conv_id, turn, text of user turns: assistant-like openers cut, prompts that talk about the assistant and repeated turns of a conversation dropped."""
    user = conv.filter("role = 'user'").withColumn("text", F.regexp_replace("text", OPENER, ""))
    user = user.filter(~F.col("text").rlike(SECOND_HAND) & (F.trim("text") != ""))
    return user.groupBy("conv_id", "text").agg(F.min("turn").alias("turn")).select("conv_id", "turn", "text")


def tree_paths(nodes: DataFrame, rounds: int = 1000) -> DataFrame:
    """tree_id, leaf, path: every path from a root to a leaf, as the list of its node ids. One join per level; levels are written."""
    from ..shared import Workspace

    space = Workspace(nodes.sparkSession, "trees")
    nodes = space.write(nodes.select("tree_id", "node_id", "parent_id"))
    level = space.write(nodes.filter("parent_id is null").select("tree_id", "node_id", F.array("node_id").alias("path")))
    children = nodes.filter("parent_id is not null").select("tree_id", F.col("parent_id").alias("up"), F.col("node_id").alias("child"))
    out = None
    for _ in range(rounds):
        next_level = level.join(children, (level["tree_id"] == children["tree_id"]) & (level["node_id"] == children["up"]), "left").select(level["tree_id"], "node_id", "path", "child")
        next_level = space.write(next_level)
        ended = next_level.filter("child is null").select("tree_id", F.col("node_id").alias("leaf"), "path")
        out = ended if out is None else out.unionByName(ended)
        level = next_level.filter("child is not null").select("tree_id", F.col("child").alias("node_id"), F.concat("path", F.array("child")).alias("path"))
        if level.isEmpty():
            return out
    raise RuntimeError(f"trees are deeper than {rounds} levels")


def simulate(contexts: DataFrame, intent: Callable[[Column], Column], user: Callable[[Column, Column, Column], Column], assistant: Callable[[Column, Column], Column], max_turns: int = 5) -> DataFrame:
    """conv_id, turn, role, text: intent agent, then user and assistant agents in turns, 1 to *max_turns* exchanges drawn by a hash of the id.

    Agents are column functions (a batch model is one behind an Arrow function) of the context, the intent and the history so far, which
    is passed at every call. The state is one row per conversation, so all rounds are map-only.
    """
    said = lambda role, text: F.array(F.struct(F.lit(role).alias("role"), text.alias("text")))
    context, goal = F.col("context"), F.col("intent")

    def exchange(history: Column, k: Column) -> Column:
        asked = F.concat(history, said("user", user(context, goal, history)))
        return F.when(k < F.col("turns"), T.let(asked, lambda h: F.concat(h, said("assistant", assistant(context, h))))).otherwise(history)

    turns = F.pmod(md5_int(F.col("conv_id")), F.lit(max_turns)) + 1
    state = contexts.select("conv_id", "context", intent(context).alias("intent"), turns.alias("turns"))
    history = F.aggregate(F.sequence(F.lit(0), F.lit(max_turns - 1)), F.array().cast("array<struct<role:string,text:string>>"), exchange)
    return state.select("conv_id", F.posexplode(history).alias("turn", "h")).select("conv_id", "turn", "h.role", "h.text")


def compare(conv: DataFrame, by: Column, name: str) -> DataFrame:
    """Per group: examples, mean turns, instruction and output length in words, type-token ratio of the instructions."""
    folded, w = T.folded_words(F.col("text")), F.size(T.words(F.col("text")))
    ratio = T.let(folded, lambda f: F.size(F.array_distinct(f)) / F.greatest(F.size(f), F.lit(1)))
    is_user = F.col("role") == "user"
    p = conv.withColumn(name, by).groupBy(name, "conv_id").agg(F.count_if(is_user).alias("t"), F.avg(F.when(is_user, w)).alias("i"), F.avg(F.when(F.col("role") == "assistant", w)).alias("o"), F.avg(F.when(is_user, ratio)).alias("r"))
    return p.groupBy(name).agg(F.count(F.lit(1)).alias("examples"), F.avg("t").alias("mean_turns"), F.avg("i").alias("instruction_len"), F.avg("o").alias("output_len"), F.avg("r").alias("diversity"))


def valid_conversations(conv: DataFrame, least: int = 2) -> DataFrame:
    """Optional system turn, then user and assistant in turns, no empty text."""
    c = conv.groupBy("conv_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", F.substring("role", 1, 1).alias("r")))), lambda x: x["r"]), "").alias("roles"), F.min(F.length("text")).alias("shortest"))
    return c.filter(F.col("roles").rlike(r"^s?(ua)+u?$") & (F.col("shortest") > 0) & (F.length("roles") >= least)).select("conv_id", "roles")


def mtld_score(words: list[str], cut: float = MTLD_CUT) -> float:
    """Mean factor length of one direction: a factor ends when the running type-token ratio falls to the cut."""
    types: set[str] = set()
    tokens, factors = 0, 0.0
    for w in words:
        tokens += 1
        types.add(w)
        if len(types) / tokens <= cut:
            factors, tokens, types = factors + 1, 0, set()
    if tokens:
        factors += (1 - len(types) / tokens) / (1 - cut)
    return len(words) / factors if factors else float(len(words))


def mtld(texts: pd.Series) -> pd.Series:
    words = [t.lower().split() if t else [] for t in texts]
    return pd.Series([(mtld_score(w) + mtld_score(w[::-1])) / 2 for w in words])


def mtld_column(words: Column, cut: float = MTLD_CUT) -> Column:
    """The same measure as a column expression over an array of words."""
    start = F.struct(F.array().cast("array<string>").alias("types"), F.lit(0).alias("tokens"), F.lit(0.0).alias("factors"))

    def more(acc: Column, w: Column) -> Column:
        def after(types: Column) -> Column:
            done = F.size(types) / (acc["tokens"] + 1) <= cut
            ended = F.struct(F.array().cast("array<string>").alias("types"), F.lit(0).alias("tokens"), (acc["factors"] + 1).alias("factors"))
            return F.when(done, ended).otherwise(F.struct(types.alias("types"), (acc["tokens"] + 1).alias("tokens"), acc["factors"].alias("factors")))

        return T.let(F.when(F.array_contains(acc["types"], w), acc["types"]).otherwise(F.array_append(acc["types"], w)), after)

    rest = lambda acc: acc["factors"] + F.when(acc["tokens"] > 0, (1 - F.size(acc["types"]) / acc["tokens"]) / (1 - cut)).otherwise(F.lit(0.0))
    one = lambda ws: T.let(F.aggregate(ws, start, more, rest), lambda f: F.when(f > 0, F.size(ws) / f).otherwise(F.size(ws).cast("double")))
    return T.let(words, lambda ws: (one(ws) + one(F.reverse(ws))) / 2)
