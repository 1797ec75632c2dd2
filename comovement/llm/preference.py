"""Preference formatting: chosen and rejected conversations become one prompt and two masked completions.

The prompt renders the longest common turn prefix (role and text equal, nulls equal to nulls) once;
each completion renders the turns after it. ``*_runs`` gives a completion's mask as signed run
lengths in characters: negative runs (headers, other roles) take no loss, positive ones do.
All is one shuffle by pair and array expressions in the JVM.

Defined results: rows without a conversation id or turn are in no conversation; a null role or text
renders as empty; turns are ordered by (turn, role, text), and repeated rows are turns of their own;
a conversation without a partner has an empty common prefix and nulls on the other side.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import pick

OPEN, MIDDLE, CLOSE = "<|", "|>\n", "<|end|>\n"


def _text(turns):
    body = F.transform(turns, lambda t: F.concat(F.lit(OPEN), F.coalesce(t["role"], F.lit("")), F.lit(MIDDLE), F.coalesce(t["text"], F.lit("")), F.lit(CLOSE)))
    return F.array_join(body, "")


def _runs(turns, trained: str):
    def runs(t):
        header = F.length(F.coalesce(t["role"], F.lit(""))) + len(OPEN) + len(MIDDLE)
        body = F.length(F.coalesce(t["text"], F.lit(""))) + len(CLOSE)
        return F.concat((-header).cast("string"), F.lit(","), F.when(F.coalesce(t["role"] == trained, F.lit(False)), body).otherwise(-body).cast("string"))

    return F.array_join(F.transform(turns, runs), ",")


def paired(turns: DataFrame, chosen: str, rejected: str, pair: str, trained: str = "assistant") -> DataFrame:
    """turns: conv_id, turn, role, text, with SQL expressions over conv_id for a row's pair and side."""
    own = pick(turns, conv_id="conv_id", turn="turn", role="role", text="text").where("conv_id is not null and turn is not null")
    turn = F.struct("turn", "role", "text")
    sides = own.groupBy(F.expr(pair).alias("pair_id")).agg(
        F.min(F.when(F.expr(chosen), F.col("conv_id"))).alias("chosen_id"),
        F.min(F.when(F.expr(rejected), F.col("conv_id"))).alias("rejected_id"),
        F.array_sort(F.collect_list(F.when(F.expr(chosen), turn))).alias("c"),
        F.array_sort(F.collect_list(F.when(F.expr(rejected), turn))).alias("r"),
    )
    n = F.least(F.size("c"), F.size("r"))
    same = F.transform(F.arrays_zip(F.slice("c", F.lit(1), n).alias("c"), F.slice("r", F.lit(1), n).alias("r")), lambda z: z["c"]["role"].eqNullSafe(z["r"]["role"]) & z["c"]["text"].eqNullSafe(z["r"]["text"]))
    first_other = F.array_position(same, F.lit(False))
    prefix = F.when(first_other > 0, first_other - 1).otherwise(n).cast("int")
    cut = sides.withColumn("n_prefix", prefix)

    def rest(side):
        return F.slice(side, F.col("n_prefix") + 1, F.greatest(F.size(side) - F.col("n_prefix"), F.lit(0)))

    return cut.select(
        "pair_id", "chosen_id", "rejected_id", F.col("n_prefix").cast("long").alias("n_prefix"),
        _text(F.slice("c", F.lit(1), F.col("n_prefix"))).alias("prompt"),
        F.when(F.col("chosen_id").isNotNull(), _text(rest("c"))).alias("chosen"),
        F.when(F.col("rejected_id").isNotNull(), _text(rest("r"))).alias("rejected"),
        F.when(F.col("chosen_id").isNotNull(), _runs(rest("c"), trained)).alias("chosen_runs"),
        F.when(F.col("rejected_id").isNotNull(), _runs(rest("r"), trained)).alias("rejected_runs"),
    )


def by_neighbours(turns: DataFrame) -> DataFrame:
    """Pairs conversations 2k (chosen) and 2k + 1 (rejected)."""
    return paired(turns, "pmod(conv_id, 2) = 0", "pmod(conv_id, 2) = 1", "(conv_id - pmod(conv_id, 2)) div 2")


def _sql() -> str:
    def text(turns: str) -> str:
        return f"coalesce(list_aggregate(list_transform({turns}, lambda t: '{OPEN}' || coalesce(t.role, '') || '{MIDDLE}' || coalesce(t.text, '') || '{CLOSE}'), 'string_agg', ''), '')"

    def runs(turns: str) -> str:
        head, body = f"length(coalesce(t.role, '')) + {len(OPEN) + len(MIDDLE)}", f"(length(coalesce(t.text, '')) + {len(CLOSE)})"
        return f"coalesce(list_aggregate(list_transform({turns}, lambda t: (-({head}))::varchar || ',' || (case when t.role = 'assistant' then {body} else -{body} end)::varchar), 'string_agg', ','), '')"

    return f"""
with own as (select conv_id, row_number() over (partition by conv_id order by turn, role nulls first, text nulls first) as i, role, text, conv_id // 2 as pair_id
             from conversations where conv_id is not null and turn is not null),
c as (select * from own where conv_id % 2 = 0), r as (select * from own where conv_id % 2 = 1),
sizes as (select pair_id, max(case when conv_id % 2 = 0 then conv_id end) as chosen_id, max(case when conv_id % 2 = 1 then conv_id end) as rejected_id,
                 least(count(*) filter (conv_id % 2 = 0), count(*) filter (conv_id % 2 = 1)) as n from own group by 1),
other as (select c.pair_id, min(c.i) - 1 as k from c join r on c.pair_id = r.pair_id and c.i = r.i
          where c.role is distinct from r.role or c.text is distinct from r.text group by 1),
cut as (select s.*, coalesce(o.k, s.n) as n_prefix from sizes s left join other o using (pair_id)),
lists as (select cut.pair_id, any_value(chosen_id) as chosen_id, any_value(rejected_id) as rejected_id, any_value(n_prefix) as n_prefix,
   coalesce(list(struct_pack(role := o.role, text := o.text) order by o.i) filter (o.conv_id % 2 = 0 and o.i <= n_prefix), []) as p,
   coalesce(list(struct_pack(role := o.role, text := o.text) order by o.i) filter (o.conv_id % 2 = 0 and o.i > n_prefix), []) as x,
   coalesce(list(struct_pack(role := o.role, text := o.text) order by o.i) filter (o.conv_id % 2 = 1 and o.i > n_prefix), []) as y
   from cut join own o using (pair_id) group by 1)
select pair_id, chosen_id, rejected_id, n_prefix::bigint as n_prefix, {text('p')} as prompt,
  case when chosen_id is not null then {text('x')} end as chosen, case when rejected_id is not null then {text('y')} end as rejected,
  case when chosen_id is not null then {runs('x')} end as chosen_runs, case when rejected_id is not null then {runs('y')} end as rejected_runs
from lists"""


ORACLE = _sql()
