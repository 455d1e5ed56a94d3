"""Chat formatting: preference pairs with a shared prompt and masked completions.

The longest common turn prefix of a chosen and a rejected conversation is rendered once as the prompt; what follows is
rendered as two completions with the character spans of assistant turns, which alone count for a loss. A rendered conversation
is one row by definition, so its turns are gathered in one place; no other group is.

Defined results: turns order by turn, role and text, so repeated rows stay in place; a null role reads as "user", a null
text as an empty one; a pair without one side has no prefix, an empty completion there and `complete` false; equal sides give
empty completions and `differs` false; an empty table gives no rows; every turn with a null conv_id is a conversation of its own,
without a partner; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Marks around a turn.
OPEN, CLOSE = "<|im_start|>", "<|im_end|>\n"


def conversations_as_arrays(turns: DataFrame) -> DataFrame:
    """(conv_id, turns array<struct<turn, role, text>>) in turn order."""
    row = F.struct(F.col("turn").cast("bigint").alias("turn"), F.coalesce(F.col("role"), F.lit("user")).alias("role"), F.coalesce(F.col("text"), F.lit("")).alias("text"))
    alone = F.when(F.col("conv_id").isNull(), F.monotonically_increasing_id())
    rows = turns.select(F.col("conv_id").cast("bigint").alias("conv_id"), alone.alias("alone"), row.alias("row"))
    return rows.groupBy("conv_id", "alone").agg(F.array_sort(F.collect_list("row")).alias("turns")).drop("alone")


def rendered(turns: Column) -> Column:
    return F.array_join(F.transform(turns, lambda x: F.concat(F.lit(OPEN), x["role"], F.lit("\n"), x["text"], F.lit(CLOSE))), "")


def assistant_spans(turns: Column) -> Column:
    """Character ranges (start, end) of assistant texts and their closing marks within the rendering."""
    start = F.struct(F.lit(0).cast("bigint").alias("at"), F.expr("cast(array() as array<struct<start: bigint, end: bigint>>)").alias("spans"))

    def step(acc: Column, x: Column) -> Column:
        begin = acc["at"] + F.length(x["role"]) + (len(OPEN) + 1)
        end = begin + F.length(x["text"]) + len(CLOSE)
        span = F.array(F.struct(begin.cast("bigint").alias("start"), end.cast("bigint").alias("end")))
        return F.struct(end.cast("bigint").alias("at"), F.when(x["role"] == "assistant", F.concat(acc["spans"], span)).otherwise(acc["spans"]).alias("spans"))

    return F.aggregate(turns, start, step, lambda acc: acc["spans"])


def spans_text(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws("-", s["start"].cast("string"), s["end"].cast("string"))), ";")


def format_preferences(pairs: DataFrame) -> DataFrame:
    """pairs: (pair_id, chosen, rejected) with arrays of struct<role, text>; either side may be null.

    Returns pair_id, n_prefix, prompt, both completions with their assistant spans, differs and complete.
    """
    out = pairs.withColumn("complete", F.col("chosen").isNotNull() & F.col("rejected").isNotNull())
    for side in ("chosen", "rejected"):
        out = out.withColumn(side, F.coalesce(side, F.expr("cast(array() as array<struct<role: string, text: string>>)")))
    differ = F.zip_with("chosen", "rejected", lambda a, b: a.isNull() | b.isNull() | ~a["role"].eqNullSafe(b["role"]) | ~a["text"].eqNullSafe(b["text"]))
    first = F.array_position(differ, F.lit(True))  # 0 where nothing differs
    out = out.withColumn("n_prefix", F.when(first > 0, first - 1).otherwise(F.size("chosen")).cast("int"))
    cut = lambda side: F.slice(F.col(side), F.col("n_prefix") + 1, F.size(side))
    return out.select(
        "pair_id",
        F.col("n_prefix").cast("bigint").alias("n_prefix"),
        rendered(F.slice("chosen", F.lit(1), F.col("n_prefix"))).alias("prompt"),
        rendered(cut("chosen")).alias("chosen_completion"),
        rendered(cut("rejected")).alias("rejected_completion"),
        assistant_spans(cut("chosen")).alias("chosen_spans"),
        assistant_spans(cut("rejected")).alias("rejected_spans"),
        ((F.size(cut("chosen")) > 0) | (F.size(cut("rejected")) > 0)).alias("differs"),
        "complete",
    )


def grafted_pairs(turns: DataFrame) -> DataFrame:
    """Pairs from plain conversations: the chosen side is a whole conversation; the rejected side leaves it before one of its
    assistant turns (number conv_id modulo their count) and goes on with the neighbouring conversation (conv_id with its lowest
    bit flipped) from that one's place on. So sides diverge at any turn, and may share turns beyond the place by chance."""
    convs = conversations_as_arrays(turns).withColumn("spots", F.filter(F.transform("turns", lambda x, i: F.when(x["role"] == "assistant", i)), lambda i: i.isNotNull()))
    place = F.get("spots", F.when(F.size("spots") > 0, F.pmod(F.coalesce("conv_id", F.lit(0)), F.size("spots"))).cast("int"))
    plain = F.transform("turns", lambda x: F.struct(x["role"].alias("role"), x["text"].alias("text")))
    whole = convs.select("conv_id", place.alias("place"), plain.alias("turns"))
    tail = F.slice("turns", F.col("place") + 1, F.size("turns"))
    other = whole.where(F.col("place").isNotNull()).select(F.col("conv_id").bitwiseXOR(F.lit(1)).alias("conv_id"), tail.alias("other"))
    joined = whole.join(other, "conv_id", "left")
    return joined.select(
        F.col("conv_id").alias("pair_id"),
        F.when(F.col("place").isNotNull(), F.col("turns")).alias("chosen"),
        F.when(F.col("place").isNotNull(), F.concat(F.slice("turns", F.lit(1), F.coalesce("place", F.lit(0))), F.col("other"))).alias("rejected"),
    )


def preference_digest(turns: DataFrame) -> DataFrame:
    out = format_preferences(grafted_pairs(turns))
    return out.withColumns({"chosen_spans": spans_text(F.col("chosen_spans")), "rejected_spans": spans_text(F.col("rejected_spans"))})


def oracle() -> str:
    """preference_digest in DuckDB SQL: both sides as turn rows, compared place by place."""
    return r"""
WITH src AS (SELECT conv_id, CASE WHEN conv_id IS NULL THEN row_number() OVER () END AS alone, turn, coalesce(role, 'user') AS role, coalesce(text, '') AS text FROM conversations),
t AS (SELECT coalesce('c' || conv_id, 'n' || alone) AS k, conv_id, role, text, row_number() OVER (PARTITION BY conv_id, alone ORDER BY turn, role, text) - 1 AS i FROM src),
spots AS (SELECT k, conv_id, i, row_number() OVER (PARTITION BY k ORDER BY i) - 1 AS nth, count(*) OVER (PARTITION BY k) AS n FROM t WHERE role = 'assistant'),
place AS (SELECT k, conv_id, i AS at FROM spots WHERE nth = ((coalesce(conv_id, 0) % n) + n) % n),
both_ AS (SELECT p.k, p.conv_id, p.at, o.k AS other, o.at AS other_at FROM place p LEFT JOIN place o ON o.conv_id = xor(p.conv_id, 1)),
sides AS (
  SELECT t.k, 'chosen' AS side, t.i, t.role, t.text FROM t JOIN both_ b USING (k)
  UNION ALL SELECT t.k, 'rejected', t.i, t.role, t.text FROM t JOIN both_ b USING (k) WHERE b.other IS NOT NULL AND t.i < b.at
  UNION ALL SELECT b.k, 'rejected', b.at + t.i - b.other_at, t.role, t.text FROM both_ b JOIN t ON t.k = b.other WHERE t.i >= b.other_at),
wide AS (SELECT k, i, max(role) FILTER (WHERE side = 'chosen') AS r1, max(text) FILTER (WHERE side = 'chosen') AS t1, max(role) FILTER (WHERE side = 'rejected') AS r2, max(text) FILTER (WHERE side = 'rejected') AS t2 FROM sides GROUP BY k, i),
prefix AS (SELECT k, coalesce(min(i) FILTER (WHERE r1 IS DISTINCT FROM r2 OR t1 IS DISTINCT FROM t2), max(i) + 1) AS n FROM wide GROUP BY k),
shown AS (SELECT s.*, p.n, '<|im_start|>' || role || chr(10) || text || '<|im_end|>' || chr(10) AS raw FROM sides s JOIN prefix p USING (k)),
placed AS (SELECT *, sum(length(raw)) OVER (PARTITION BY k, side ORDER BY i) - length(raw) AS before FROM shown WHERE i >= n),
done AS (SELECT k, side, string_agg(raw, '' ORDER BY i) AS completion, string_agg(CAST(before + length(role) + 13 AS BIGINT)::VARCHAR || '-' || CAST(before + length(raw) AS BIGINT)::VARCHAR, ';' ORDER BY i) FILTER (WHERE role = 'assistant') AS spans FROM placed GROUP BY k, side),
prompt AS (SELECT k, string_agg(raw, '' ORDER BY i) AS prompt FROM shown WHERE side = 'chosen' AND i < n GROUP BY k)
SELECT x.conv_id AS pair_id, CAST(coalesce(prefix.n, 0) AS BIGINT) AS n_prefix, coalesce(prompt.prompt, '') AS prompt,
  coalesce(c.completion, '') AS chosen_completion, coalesce(r.completion, '') AS rejected_completion, coalesce(c.spans, '') AS chosen_spans, coalesce(r.spans, '') AS rejected_spans,
  c.k IS NOT NULL OR r.k IS NOT NULL AS differs, coalesce(b.other IS NOT NULL, false) AS complete
FROM (SELECT DISTINCT k, conv_id FROM t) x LEFT JOIN both_ b USING (k) LEFT JOIN prefix USING (k) LEFT JOIN prompt USING (k)
LEFT JOIN done c ON c.k = x.k AND c.side = 'chosen' LEFT JOIN done r ON r.k = x.k AND r.side = 'rejected'
"""
