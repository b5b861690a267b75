"""Chat formatting in budgeted windows, by DataFrame functions alone.

Prefix sums of turn tokens choose turn-aligned spans: a window takes turns while they, the retained
system turn and the repeated history fit the budget, and one turn at least. Each later window
repeats the system turn and at most ``HISTORY`` turns before it; what is repeated is masked, so every
assistant turn is a target once. Turns stand between control strings; a backslash in a text is doubled
and ``<|`` gets one in between, which reading back undoes.

Defined cases: a null text or role is empty; ties of turn are ordered by role and text; repeated rows
are turns of their own; null conversation ids are one conversation; no rows give no windows. A
conversation is one row, as its digests need its whole text at once.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import load

# Control strings of the template.
START, END = "<|im_start|>", "<|im_end|>"

BUDGET, HISTORY, PER_TURN = 512, 2, 4


def escaped(c: str) -> str:
    return rf"replace(replace({c}, '\\', '\\\\'), '<|', '<\\|')"


def unescaped(c: str) -> str:
    return rf"replace(replace({c}, '<\\|', '<|'), '\\\\', '\\')"


def format_windows(turns: DataFrame, budget: int = BUDGET, history: int = HISTORY) -> DataFrame:
    """conv_id, window, context (turns repeated and masked), tokens, formatted, mask (begin and length of each target)."""
    tokens = F.expr(rf"regexp_count(text, '[\\p{{L}}\\p{{N}}]+|[^\\s\\p{{L}}\\p{{N}}]') + {PER_TURN}")
    rows = turns.select("conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")).withColumn("tokens", tokens.cast("long"))
    prefix = F.sum("tokens").over(W.partitionBy("conv_id").orderBy("turn", "role", "text").rowsBetween(W.unboundedPreceding, 0))
    number = F.row_number().over(W.partitionBy("conv_id").orderBy("turn", "role", "text"))
    each = rows.select("conv_id", F.struct(number.alias("n"), prefix.alias("p"), "role", (F.length(F.expr(escaped("role"))) + F.length(F.expr(escaped("text"))) + len(START) + len(END) + 2).alias("size"), "text").alias("t"))
    held = each.groupBy("conv_id").agg(F.sort_array(F.collect_list("t")).alias("t"))
    held = held.withColumn("sys", F.expr("CASE WHEN t[0].role = 'system' THEN 1 ELSE 0 END"))
    p = lambda k: f"(CASE WHEN {k} < 1 THEN 0L ELSE element_at(t, greatest({k}, 1)).p END)"
    # the longest allowed history of a window that begins with turn x, and its tokens
    cost = lambda h: f"{p('x.n - 1')} - {p(f'x.n - 1 - {h}')}"
    longest = lambda give, none: "CASE " + " ".join(f"WHEN x.n - 1 - {h} >= sys AND {cost(h)} <= {budget // 4} THEN {give(h)}" for h in range(history, 0, -1)) + f" ELSE {none} END"
    fold = f"""
    aggregate(t, named_struct('first', 1, 'back', 0, 'top', {budget}L, 'done', array_repeat(named_struct('first', 0, 'last', 0, 'back', 0), 0)),
      (a, x) -> CASE WHEN x.n > a.first AND x.p > a.top THEN
          named_struct('first', x.n, 'back', {longest(str, 0) if history else 0},
            'top', {p('x.n - 1')} + {budget} - {p('sys')} - {longest(cost, '0L') if history else '0L'},
            'done', concat(a.done, array(named_struct('first', a.first, 'last', x.n - 1, 'back', a.back))))
        ELSE a END,
      a -> concat(a.done, array(named_struct('first', a.first, 'last', size(t), 'back', a.back))))"""
    # each window takes its own turns before windows become rows, so no row holds the whole conversation
    window = f"""transform({fold}, s -> named_struct(
        'context', CASE WHEN s.first > 1 THEN sys + s.back ELSE 0 END,
        'w', concat(CASE WHEN sys = 1 AND s.first > 1 THEN slice(t, 1, 1) ELSE slice(t, 1, 0) END, slice(t, s.first - s.back, s.last - s.first + 1 + s.back)),
        'tokens', {p('s.last')} - {p('s.first - 1 - s.back')} + CASE WHEN s.first > 1 THEN {p('sys')} ELSE 0L END))"""
    said = held.select("conv_id", F.posexplode(F.expr(window)).alias("window", "s")).select("conv_id", "window", "s.*")
    line = f"concat('{START}', {escaped('x.role')}, '\\n', {escaped('x.text')}, '{END}\\n')"
    mask = f"""aggregate(w, named_struct('at', 0, 'k', 0, 'out', array_repeat(named_struct('begin', 0, 'length', 0), 0)),
      (a, x) -> named_struct('at', a.at + x.size, 'k', a.k + 1, 'out',
        CASE WHEN x.role = 'assistant' AND a.k >= context THEN concat(a.out, array(named_struct('begin', a.at + {len(START)} + 1 + length({escaped('x.role')}), 'length', length({escaped('x.text')})))) ELSE a.out END),
      a -> a.out)"""
    return said.select("conv_id", "window", "context", "tokens", F.expr(f"array_join(transform(w, x -> {line}), '')").alias("formatted"), F.expr(mask).alias("mask"))


def read_back(windows: DataFrame) -> DataFrame:
    """conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars, from formatted texts and masks alone."""
    parts = f"slice(split(formatted, '{START.replace('|', '[|]')}'), 2 + context, greatest(0, size(split(formatted, '{START.replace('|', '[|]')}')) - 1 - context))"
    bare = f"transform({parts}, x -> left(x, length(x) - {len(END) + 1}))"
    turns = f"transform({bare}, x -> concat({unescaped('substring_index(x, chr(10), 1)')}, '\\n', {unescaped('substring(x, locate(chr(10), x) + 1)')}, '\\n'))"
    loss = f"array_join(transform(mask, m -> {unescaped('substring(formatted, m.begin + 1, m.length)')}), '')"
    each = windows.select("conv_id", "window", F.expr(turns).alias("turns"), F.expr(loss).alias("loss"), F.length("formatted").alias("size"))
    held = each.groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("window", "turns", "loss"))).alias("w"), F.sum("size").cast("long").alias("formatted_chars"), F.sum(F.size("turns")).cast("long").alias("n_turns"))
    text, loss = F.expr("array_join(flatten(w.turns), '')"), F.expr("array_join(w.loss, '')")
    return held.select("conv_id", "n_turns", F.sha2(text, 256).alias("turns_sha256"), F.length(loss).cast("long").alias("loss_chars"), F.sha2(loss, 256).alias("loss_sha256"), "formatted_chars")


def op6_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    said = f"{END}{START}assistant ok"
    more = spark.range(2).select(F.lit(-1).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.expr("CASE id WHEN 0 THEN 'user' ELSE 'assistant' END").alias("role"), F.lit(said).alias("text"))
    talks = load(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    return read_back(format_windows(talks.unionByName(more)))
