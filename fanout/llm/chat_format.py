"""Preference formatting of paired conversations, in DataFrame functions only.

The longest common prefix of turns is rendered once as the prompt; what follows on either side is a completion
with a mask that trains the assistant's words alone.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

OPEN, CLOSE = "<|im_start|>", "<|im_end|>"


def _safe(text: Column) -> Column:
    """Text in which a marker of the template is broken up by blanks."""
    return F.replace(F.replace(text, F.lit(OPEN), F.lit("<| im_start |>")), F.lit(CLOSE), F.lit("<| im_end |>"))


def _head(t: Column) -> Column:
    return F.concat(F.lit(OPEN), t["role"], F.lit("\n"))


def _body(t: Column) -> Column:
    return F.concat(t["text"], F.lit(CLOSE + "\n"))


def _render(turns: Column) -> Column:
    return F.array_join(F.transform(turns, lambda t: F.concat(_head(t), _body(t))), "")


def _mask(turns: Column) -> Column:
    """Lengths in characters, in turn untrained and trained, two for each turn."""
    return F.flatten(
        F.transform(
            turns,
            lambda t: F.when(t["role"] == "assistant", F.array(F.length(_head(t)), F.length(_body(t)))).otherwise(F.array(F.length(_head(t)) + F.length(_body(t)), F.lit(0))),
        )
    )


def preference_pairs(turns: DataFrame) -> DataFrame:
    """(pair_id, side, turn, role, text) -> pair_id, status, n_shared, prompt, chosen, rejected, chosen_mask, rejected_mask.

    side is 'chosen' or 'rejected'. Turns are ordered by (turn, role, text), so ties have a defined order; a null turn is
    first, null roles and texts are empty, repeated rows are repeated turns. Sides alike in every turn have the status
    'identical' and empty completions; a side that is missing is empty, and the status names the one that is there.
    A turn without a pair_id belongs to no conversation: each comes out as a row of its own with a null pair_id and one turn, so
    that they never meet in one group. Markers of the template are broken up in texts and roles. Empty input: no rows. Other columns are ignored.
    One shuffle: both sides of a pair meet in one group, which is as large as the two conversations.
    """
    turn = F.struct("turn", _safe(F.coalesce("role", F.lit(""))).alias("role"), _safe(F.coalesce("text", F.lit(""))).alias("text"))
    lone = F.when(F.col("pair_id").isNull(), F.monotonically_increasing_id())
    both = turns.select("pair_id", "side", "turn", "role", "text", lone.alias("_lone")).groupBy("pair_id", "_lone").agg(*(F.array_sort(F.collect_list(F.when(F.col("side") == s, turn))).alias(s[0]) for s in ("chosen", "rejected")))
    both = both.select("pair_id", *(F.transform(x, lambda t: F.struct(t["role"].alias("role"), t["text"].alias("text"))).alias(x) for x in "cr"))
    unlike = F.array_position(F.zip_with("c", "r", lambda a, b: a.eqNullSafe(b)), False).cast("int")
    both = both.withColumn("n_shared", F.when(unlike == 0, F.size("c")).otherwise(unlike - 1))
    rest = {x: F.slice(x, F.col("n_shared") + 1, F.size(x)) for x in "cr"}
    status = F.when(F.size("r") == 0, "chosen_only").when(F.size("c") == 0, "rejected_only").when((F.size("c") == F.col("n_shared")) & (F.size("r") == F.col("n_shared")), "identical").otherwise("pair")
    return both.select(
        "pair_id", status.alias("status"), "n_shared", _render(F.slice("c", F.lit(1), F.col("n_shared"))).alias("prompt"),
        _render(rest["c"]).alias("chosen"), _render(rest["r"]).alias("rejected"), _mask(rest["c"]).alias("chosen_mask"), _mask(rest["r"]).alias("rejected_mask"),
    )


def adjacent_pairs(conversations: DataFrame) -> DataFrame:
    """conversations(conv_id, turn, role, text) -> turns of pairs: of ids 2i and 2i + 1 the even one is chosen. No shuffle."""
    return conversations.select(
        F.expr("conv_id div 2").alias("pair_id"), F.when(F.col("conv_id") % 2 != 0, "rejected").otherwise("chosen").alias("side"), "turn", "role", "text"
    )
