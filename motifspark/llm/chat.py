"""Chat formatting with cumulative-snapshot collapse.

Logs often hold a conversation several times, each snapshot a turn or two longer. A rolling hash over the turns gives
every prefix of a conversation a name; a conversation whose whole hash is a proper prefix of another one is a snapshot
and goes by an anti-join. Equal conversations keep the least id. Only what stays is rendered.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable


@dataclass(frozen=True)
class ChatTemplate:
    """Markers around each turn; in contents ``guard`` is broken up, so that no text can pose as a marker."""

    before: str = "<|im_start|>"
    between: str = "\n"
    after: str = "<|im_end|>\n"
    guard: str = "<|"
    guarded: str = "< |"


def conversations(turns: DataFrame, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """``conv_id, alone, turns, prefixes``: the ordered turns and the rolling hash after each of them.

    Repeated rows count once; turns that tie in number are ordered by role, then text; a null number comes first. A
    null role is ``unknown``, a null text empty. Each distinct row with a null conversation id is a conversation of its
    own, told apart by the hash ``alone``, so such rows never gather in one task.
    """
    one = F.struct(
        F.col(turn_col).cast("long").alias("turn"),
        F.coalesce(F.col(role_col).cast("string"), F.lit("unknown")).alias("role"),
        F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"),
    )
    own = turns.select(F.col(conv_col).alias("conv_id"), one.alias("one"))
    alone = F.when(F.col("conv_id").isNull(), F.sha2(F.to_json("one"), 256))
    own = own.withColumn("alone", alone).groupBy("conv_id", "alone").agg(F.array_sort(F.collect_set("one")).alias("turns"))
    rolled = F.expr(
        """aggregate(turns, struct('' as h, cast(array() as array<string>) as all),
             (a, t) -> transform(array(sha2(concat(a.h, '|', length(t.role), '|', t.role, t.text), 256)), h -> struct(h as h, concat(a.all, array(h)) as all))[0],
             a -> a.all)"""
    )
    return own.withColumn("prefixes", rolled)


def maximal(convs: DataFrame) -> DataFrame:
    """``conv_id, alone, n_copies`` of the conversations that no longer one continues, the least id of equal ones."""
    least = F.min(F.struct(F.col("conv_id").isNull(), "conv_id", "alone"))
    whole = convs.groupBy(F.element_at("prefixes", -1).alias("h")).agg(least.alias("c"), F.count("*").alias("n_copies"))
    shorter = convs.select(F.explode(F.expr("slice(prefixes, 1, size(prefixes) - 1)")).alias("h")).distinct()
    return whole.join(shorter, "h", "left_anti").select("c.conv_id", "c.alone", "n_copies")


def format_chats(turns: DataFrame, template: ChatTemplate | None = None, **columns: str) -> DataFrame:
    """``conv_id, n_turns, n_copies, text`` of every maximal conversation, rendered; an empty table gives no row."""
    t = template or ChatTemplate()
    convs = durable(conversations(turns, **columns))
    kept = maximal(convs).select(F.col("conv_id").alias("i"), F.col("alone").alias("a"), "n_copies")
    kept = convs.join(kept, F.col("conv_id").eqNullSafe(F.col("i")) & F.col("alone").eqNullSafe(F.col("a")))
    lit = lambda x: F.lit(x)
    clean = lambda c: F.replace(c, lit(t.guard), lit(t.guarded))
    each = F.transform("turns", lambda x: F.concat(lit(t.before), clean(x["role"]), lit(t.between), clean(x["text"]), lit(t.after)))
    return kept.select("conv_id", F.size("turns").cast("long").alias("n_turns"), "n_copies", F.array_join(each, "").alias("text"))


ORACLE_SQL = r"""
WITH own AS (SELECT DISTINCT conv_id, turn, coalesce(role, 'unknown') AS role, coalesce(text, '') AS text FROM conversations),
whole AS (
  SELECT conv_id, count(*) AS n_turns,
         string_agg(length(role) || '|' || role || length(text) || '|' || text || chr(30), '' ORDER BY turn, role, text) AS k,
         string_agg('<|im_start|>' || replace(role, '<|', '< |') || chr(10) || replace(text, '<|', '< |') || '<|im_end|>' || chr(10), '' ORDER BY turn, role, text) AS text
  FROM own GROUP BY conv_id, CASE WHEN conv_id IS NULL THEN coalesce(turn::VARCHAR, '') || '|' || length(role) || '|' || role || text END),
one AS (SELECT k, min(conv_id) AS conv_id, any_value(n_turns) AS n_turns, any_value(text) AS text, count(*) AS n_copies FROM whole GROUP BY k)
SELECT o.conv_id, o.n_turns, o.n_copies, o.text
FROM one o
WHERE NOT EXISTS (SELECT 1 FROM one b WHERE length(b.k) > length(o.k) AND starts_with(b.k, o.k))
"""
