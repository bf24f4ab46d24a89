"""Preference pairs for training: one prompt, two masked completions.

The longest common prefix of turns of the chosen and the rejected conversation
is rendered once as the prompt; what follows on either side is a completion,
with the spans of the assistant's words in it as its mask.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nudgegraph.llm.text import need

#: fixed: how a turn is rendered, before its role, before its text and after it
OPEN, MIDDLE, CLOSE = "<|im_start|>", "\n", "<|im_end|>\n"


def _render(turn: F.Column) -> F.Column:
    return F.concat(F.lit(OPEN), turn["role"], F.lit(MIDDLE), turn["text"], F.lit(CLOSE))


def _text(turns: F.Column) -> F.Column:
    return F.array_join(F.transform(turns, _render), "")


def _mask(turns: F.Column) -> F.Column:
    """(start, end) in characters of each assistant turn's text and end mark."""
    empty = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<start:int,end:int>>").alias("spans"))

    def step(so_far, turn):
        begin = so_far["at"] + F.length(turn["role"]) + len(OPEN) + len(MIDDLE)
        end = begin + F.length(turn["text"]) + len(CLOSE)
        mine = F.array(F.struct(begin.alias("start"), end.alias("end")))
        return F.struct(end.alias("at"), F.when(turn["role"] == "assistant", F.concat(so_far["spans"], mine)).otherwise(so_far["spans"]).alias("spans"))

    return F.aggregate(turns, empty, step, lambda x: x["spans"])


def format_preferences(turns: DataFrame) -> DataFrame:
    """(pair_id, n_common, n_chosen, n_rejected, prompt, chosen, rejected, chosen_mask, rejected_mask) per pair.

    ``turns``: (pair_id, chosen as boolean, turn, role, text). Turns are in the
    order of turn, role and text, nulls first; two are common if role and text
    are equal. A null text counts as empty, a null role as ``unknown``. A side
    without turns is an empty conversation; repeated rows are turns of their
    own. Rows with a null pair_id or side belong to no pair and are left out.
    """
    own = need(turns, "pair_id", "chosen", "turn", "role", "text").where("pair_id is not null and chosen is not null")
    one = F.struct("turn", F.coalesce("role", F.lit("unknown")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    side = lambda which: F.array_sort(F.collect_list(F.when(F.col("chosen") == which, one)), _by_place)
    pairs = own.groupBy("pair_id").agg(side(True).alias("c"), side(False).alias("r"))
    shorter = F.least(F.size("c"), F.size("r"))

    def step(n, i):
        a, b = F.element_at("c", i), F.element_at("r", i)
        return F.when((n == i - 1) & (a["role"] == b["role"]) & (a["text"] == b["text"]), i).otherwise(n)

    common = F.when(shorter > 0, F.aggregate(F.sequence(F.lit(1), F.greatest(shorter, F.lit(1))), F.lit(0), step)).otherwise(0)
    pairs = pairs.withColumn("n_common", common)
    rest = lambda x: F.slice(F.col(x), F.col("n_common") + 1, F.size(x))
    return pairs.select(
        "pair_id", F.col("n_common").cast("int").alias("n_common"), F.size("c").alias("n_chosen"), F.size("r").alias("n_rejected"),
        _text(F.slice("c", F.lit(1), F.col("n_common"))).alias("prompt"), _text(rest("c")).alias("chosen"), _text(rest("r")).alias("rejected"),
        _mask(rest("c")).alias("chosen_mask"), _mask(rest("r")).alias("rejected_mask"),
    )


def _by_place(a: F.Column, b: F.Column) -> F.Column:
    """Order by turn, role and text, a null turn first."""
    key = lambda x: F.struct(x["turn"].isNotNull(), x["turn"], x["role"], x["text"])
    return F.when(key(a) < key(b), -1).when(key(a) > key(b), 1).otherwise(0)


def demo_pairs(conversations: DataFrame) -> DataFrame:
    """Each conversation against itself with another's last answer: pairs that share all turns before it.

    The chosen side is the conversation. The rejected side is its turns before
    its last assistant turn, then the last answer of its neighbour by id (0
    with 1, 2 with 3, ...), an empty one where there is none. Without an
    assistant turn both sides are alike. Rows with a null id are left out.
    """
    own = need(conversations, "conv_id", "turn", "role", "text").where("conv_id is not null").withColumn("text", F.coalesce("text", F.lit("")))
    place = F.struct(F.col("turn").isNotNull(), "turn", "text")
    last = own.where("role = 'assistant'").groupBy("conv_id").agg(F.max_by(F.struct("turn", "text"), place).alias("last"))
    other = last.select(F.col("conv_id").bitwiseXOR(F.lit(1).cast("long")).alias("conv_id"), F.col("last.text").alias("answer"))
    ends = last.join(other, "conv_id", "left").select("conv_id", "last", F.coalesce("answer", F.lit("")).alias("answer"))
    at = lambda turn, role, text: F.struct(turn.isNotNull(), turn, role, text)
    before = at(F.col("turn"), F.coalesce("role", F.lit("unknown")), F.col("text")) < at(F.col("last.turn"), F.lit("assistant"), F.col("last.text"))
    kept = own.join(ends, "conv_id", "left").where(F.col("last").isNull() | before).select("conv_id", "turn", "role", "text")
    answer = ends.select("conv_id", F.col("last.turn").alias("turn"), F.lit("assistant").alias("role"), F.col("answer").alias("text"))
    sides = [(own.select("conv_id", "turn", "role", "text"), True), (kept, False), (answer, False)]
    made = [df.select(F.col("conv_id").cast("long").alias("pair_id"), F.lit(chosen).alias("chosen"), "turn", "role", "text") for df, chosen in sides]
    return made[0].unionByName(made[1]).unionByName(made[2])


def spans_text(column: str) -> F.Column:
    """A mask as text, such as 12-40,71-95."""
    return F.array_join(F.transform(column, lambda s: F.concat(s["start"].cast("string"), F.lit("-"), s["end"].cast("string"))), ",")


ORACLE = """
with c as (select conv_id, turn, coalesce(role, 'unknown') as role, coalesce(text, '') as text from conversations where conv_id is not null),
l as (select conv_id, arg_max(turn, (turn, text)) as turn, arg_max(text, (turn, text)) as text from c where role = 'assistant' group by conv_id),
ends as (select l.conv_id, l.turn, l.text, coalesce(o.text, '') as answer from l left join l o on o.conv_id = xor(l.conv_id, 1)),
u as (
  select conv_id, true as chosen, turn, role, text from c
  union all select c.conv_id, false, c.turn, c.role, c.text from c left join ends e on e.conv_id = c.conv_id
    where e.conv_id is null or c.turn < e.turn or (c.turn = e.turn and (c.role < 'assistant' or (c.role = 'assistant' and c.text < e.text)))
  union all select conv_id, false, turn, 'assistant', answer from ends
), t as (
  select conv_id as pair_id, chosen, role, text, row_number() over (partition by conv_id, chosen order by turn nulls first, role, text) as i from u
), same as (
  select a.pair_id, a.i, row_number() over (partition by a.pair_id order by a.i) as nth
  from t a join t b on a.pair_id = b.pair_id and a.i = b.i and a.role = b.role and a.text = b.text
  where a.chosen and not b.chosen
), common as (select pair_id, count(*) as n from same where i = nth group by pair_id),
r as (
  select t.*, coalesce(c.n, 0) as n, '<|im_start|>' || role || chr(10) || text || '<|im_end|>' || chr(10) as s
  from t left join common c on c.pair_id = t.pair_id
), placed as (
  select *, sum(case when i > n then length(s) else 0 end) over (partition by pair_id, chosen order by i) as upto from r
)
select pair_id, max(n)::integer as n_common, (count(*) filter (chosen))::integer as n_chosen, (count(*) filter (not chosen))::integer as n_rejected,
       coalesce(string_agg(s, '' order by i) filter (chosen and i <= n), '') as prompt,
       coalesce(string_agg(s, '' order by i) filter (chosen and i > n), '') as chosen,
       coalesce(string_agg(s, '' order by i) filter (not chosen and i > n), '') as rejected,
       coalesce(string_agg((upto - length(text) - 11)::integer || '-' || upto::integer, ',' order by i) filter (chosen and i > n and role = 'assistant'), '') as chosen_mask,
       coalesce(string_agg((upto - length(text) - 11)::integer || '-' || upto::integer, ',' order by i) filter (not chosen and i > n and role = 'assistant'), '') as rejected_mask
from placed group by pair_id
"""
