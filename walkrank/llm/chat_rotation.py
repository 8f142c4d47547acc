"""Chat transcripts from the view of each participant.

For every participant of a conversation all turns are rendered with that speaker as the assistant and the others as
users with their names; turns of the system stay so. The mask trains on what the assistant says and its end mark.

A conversation is rendered in parts of `part_turns` turn numbers, so a very long one is never gathered in one task; the
parts of a view in order (part, then sub) make up the whole. Each row has the text and its mask as runs
"mask:characters". Where a part has more than `most` rows (turns without a number, or of one number, are one part) it is
cut by turn number, and the rows of one number by a hash of what they say; rows that repeat are counted before, and
very many copies are spread too. So no task gathers more than about `most` rows of a part.

In texts and names "<|" is written "< |", and a line end in a name is a space: nobody can end a turn, start another one or
move the mask by what they say or are called.

A null role is the speaker `unknown`; a null text is empty; turns without a number make up the part null, which comes
first; rows without a conv_id are one conversation. Turns of one number come in order of speaker and text, repeated
rows as often as they are. A conversation with turns of the system alone has no view. Other columns are left out; an
empty table gives an empty table. Only DataFrame functions are used.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

PART_TURNS, MOST = 64, 1024
BEGIN, END, SYSTEM, UNKNOWN = "<|im_start|>", "<|im_end|>", "system", "unknown"
#: Chunks of a turn number that a sub has room for.
CHUNKS = 1 << 20


def plain(text: Column) -> Column:
    """What is said or a name, without marks."""
    return F.replace(text, F.lit("<|"), F.lit("< |"))


def header(speaker: Column, view: Column) -> Column:
    """The start of a turn, up to what is said."""
    who = F.when(speaker == SYSTEM, F.lit(SYSTEM)).when(speaker == view, F.lit("assistant")).otherwise(F.concat(F.lit("user name="), speaker))
    return F.concat(F.lit(BEGIN), who, F.lit("\n"))


def chunked(said: DataFrame, part_turns: int, most: int) -> DataFrame:
    """Turns, how often they come (times), and the sub of their part; 0 where the part is not crowded."""
    key = lambda *names: [F.col(n).eqNullSafe(F.col(f"_{n}")) for n in names]
    sized = said.groupBy("conv_id", "part").count().where(F.col("count") > most)
    sized = common.written(sized.select(F.col("conv_id").alias("_conv_id"), F.col("part").alias("_part")), "chat-crowded")
    whole = lambda df: df.select("*", F.lit(1).cast("long").alias("times"), F.lit(0).cast("long").alias("sub"))
    if sized.isEmpty():  # the usual case: nothing but the counts was read twice
        return whole(said)
    crowded = said.join(sized, key("conv_id", "part"), "left_semi").groupBy(*said.columns).agg(F.count("*").alias("times"))
    quiet = whole(said.join(sized, key("conv_id", "part"), "left_anti"))
    turns = crowded.groupBy("conv_id", "turn").agg(F.ceil(F.sum("times") / most).cast("long").alias("chunks"))
    turns = turns.select(F.col("conv_id").alias("_conv_id"), F.col("turn").alias("_turn"), "chunks")
    dealt = crowded.join(turns, key("conv_id", "turn"))
    last = F.ceil(F.col("times") / most).cast("long") - 1
    dealt = dealt.select("conv_id", "part", "turn", "role", "text", "times", "chunks", F.explode(F.sequence(F.lit(0).cast("long"), last)).alias("copy"))
    spread = F.conv(F.substring(F.md5(F.concat("role", F.lit("\n"), "text")), 1, 7), 16, 10).cast("long")
    sub = F.coalesce(F.col("turn") - F.col("part") * part_turns, F.lit(0)) * CHUNKS + F.pmod(spread + F.col("copy"), F.col("chunks"))
    return quiet.unionByName(dealt.select("conv_id", "part", "turn", "role", "text", F.least(F.lit(most), F.col("times") - F.col("copy") * most).alias("times"), sub.alias("sub")))


def rotated(turns: DataFrame, part_turns: int = PART_TURNS, most: int = MOST) -> DataFrame:
    """turns: conv_id, turn, role, text. conv_id, view, part, sub, n_turns, n_trained (characters), text, mask_runs."""
    role = F.replace(plain(F.coalesce("role", F.lit(UNKNOWN))), F.lit("\n"), F.lit(" "))
    said = turns.select("conv_id", F.floor(F.col("turn") / part_turns).cast("long").alias("part"), F.col("turn").cast("long").alias("turn"), role.alias("role"), plain(common.text_of()).alias("text"))
    views = said.where(F.col("role") != SYSTEM).select(F.col("conv_id").alias("_conv"), F.col("role").alias("view")).distinct()
    parts = chunked(said, part_turns, most).groupBy("conv_id", "part", "sub").agg(F.sort_array(F.collect_list(F.struct("turn", "role", "text", "times"))).alias("turns"))
    parts = parts.withColumn("turns", F.flatten(F.transform("turns", lambda t: F.array_repeat(t, t.times.cast("int")))))
    rows = parts.join(views, F.col("conv_id").eqNullSafe(F.col("_conv")))
    view, tail = F.col("view"), F.lit(END + "\n")
    whole = F.array_join(F.transform("turns", lambda t: F.concat(header(t.role, view), t.text, tail)), "")
    own = lambda t: (t.role == view) & (t.role != SYSTEM)
    trained = lambda t: F.length(t.text) + len(END)
    run = lambda t: F.when(own(t), F.concat(F.lit("0:"), F.length(header(t.role, view)), F.lit(",1:"), trained(t), F.lit(",0:1"))).otherwise(F.concat(F.lit("0:"), F.length(header(t.role, view)) + F.length(t.text) + len(END) + 1))
    return rows.select(
        "conv_id", "view", "part", "sub", F.size("turns").cast("long").alias("n_turns"),
        F.aggregate("turns", F.lit(0).cast("long"), lambda s, t: s + F.when(own(t), trained(t)).otherwise(0)).alias("n_trained"),
        whole.alias("text"), F.array_join(F.transform("turns", run), ",").alias("mask_runs"),
    )


def op9_chat_rotation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every conversation from each participant's view."""
    return rotated(common.documents(spark, sf_dir, "conversations"))


QUERIES = {"op9_chat_rotation": op9_chat_rotation}
ORACLES = {
    "op9_chat_rotation": f"""
with said as (select conv_id, floor(turn / {PART_TURNS}.0)::bigint as part, turn::bigint as turn, replace(replace(coalesce(role, '{UNKNOWN}'), '<|', '< |'), chr(10), ' ') as role,
          replace(coalesce(text, ''), '<|', '< |') as text, count(*) as times from conversations group by all),
views as (select distinct conv_id, role as view from said where role <> '{SYSTEM}'),
sized as (select *, sum(times) over (partition by conv_id, part) as rows_, sum(times) over (partition by conv_id, turn) as same,
          ('0x' || substr(md5(role || chr(10) || text), 1, 7))::bigint as spread from said),
copies as (select *, unnest(range(0, ((times + {MOST - 1}) // {MOST})::bigint)) as copy from sized),
dealt as (select conv_id, part, turn, role, text, least({MOST}, times - copy * {MOST}) as times,
          case when rows_ <= {MOST} then 0 else coalesce(turn - part * {PART_TURNS}, 0) * {CHUNKS} + (spread + copy) % ((same + {MOST - 1}) // {MOST})::bigint end as sub from copies),
seg as (select s.conv_id, v.view, s.part, s.sub, s.turn, s.role, s.text, s.times, s.role = v.view as own,
          '{BEGIN}' || case when s.role = '{SYSTEM}' then '{SYSTEM}' when s.role = v.view then 'assistant' else 'user name=' || s.role end || chr(10) as head
        from dealt s join views v on s.conv_id is not distinct from v.conv_id),
runs as (select *, case when own then '0:' || length(head) || ',1:' || (length(text) + {len(END)}) || ',0:1' else '0:' || (length(head) + length(text) + {len(END)} + 1) end as run from seg)
select conv_id, view, part, sub::bigint as sub, sum(times)::bigint as n_turns,
  coalesce(sum(times * (length(text) + {len(END)})) filter (where own), 0)::bigint as n_trained,
  string_agg(repeat(head || text || '{END}' || chr(10), times::bigint), '' order by turn nulls first, role, text) as text,
  string_agg(run || repeat(',' || run, times::bigint - 1), ',' order by turn nulls first, role, text) as mask_runs
from runs group by conv_id, view, part, sub"""
}
