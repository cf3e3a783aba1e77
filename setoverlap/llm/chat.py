"""Chat formatting by a grammar round trip, in built-in functions only.

A turn is written as  ### role:\ntext\n</turn>\n .  Texts go in raw; a deterministic parser reads the
rendering back, and a turn that does not come back as it was is written again with its control strings
escaped by a backslash; a conversation that still differs is escaped as a whole and read once more, and one that
would not come back even then fails the job. In roles a backslash, a colon and "<" are always escaped, so that no
role can close its own head or a turn. What the query reports is read back from the output alone.

Defined cases: null role or text reads as empty; turns are ordered by turn, then role, then text (ties and
repeated rows stay, null turns come first); rows with a null conv_id form one conversation; an empty table gives
an empty result; other columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

CONTROL = r"\\|###|</turn>"
ESCAPED = r"\\(\\|###|</turn>)"
END = "\n</turn>\n"
ROLE_CONTROL = r"[\\:<]"
HEAD = r"(?s)^### ((?:[^\\:]|\\.)*+):\n"


def escape(text: Column) -> Column:
    return F.regexp_replace(text, CONTROL, r"\\$0")


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, ESCAPED, "$1")


def render_turn(role: Column, body: Column) -> Column:
    return F.concat(F.lit("### "), F.regexp_replace(role, ROLE_CONTROL, r"\\$0"), F.lit(":\n"), body, F.lit(END))


def parse(formatted: Column) -> Column:
    """The turns that a formatted conversation holds: array of (role, text)."""
    parts = F.split(formatted, END)
    parts = F.slice(parts, F.lit(1), F.greatest(F.size(parts) - 1, F.lit(0)))

    def turn(p: Column) -> Column:
        head = F.regexp_extract(p, HEAD, 0)
        role = F.regexp_replace(F.regexp_extract(p, HEAD, 1), r"(?s)\\(.)", "$1")
        return F.struct(role.alias("role"), unescape(F.substring(p, F.length(head) + 1, F.length(p))).alias("text"))

    return F.transform(parts, turn)


def format_conversations(df: DataFrame) -> DataFrame:
    """conv_id, turns (array of role and text), formatted (string), one row a conversation."""
    row = F.struct(F.col("turn").cast("long").alias("turn"), F.coalesce(F.col("role").cast("string"), F.lit("")).alias("role"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    got = df.groupBy(F.col("conv_id").cast("long").alias("conv_id")).agg(F.sort_array(F.collect_list(row)).alias("rows"))
    got = got.select("conv_id", F.transform("rows", lambda x: F.struct(x["role"].alias("role"), x["text"].alias("text"))).alias("turns"))

    def render(x: Column) -> Column:
        raw = render_turn(x["role"], x["text"])
        return F.when(parse(raw) == F.array(x), raw).otherwise(render_turn(x["role"], escape(x["text"])))

    got = got.withColumn("first", F.array_join(F.transform("turns", render), ""))
    whole = F.array_join(F.transform("turns", lambda x: render_turn(x["role"], escape(x["text"]))), "")
    got = got.withColumn("whole", F.when(parse(F.col("first")) != F.col("turns"), whole))
    wrong = F.raise_error(F.concat(F.lit("conversation does not come back: "), F.col("conv_id").cast("string")))
    formatted = F.when(F.col("whole").isNull(), F.col("first")).when(parse(F.col("whole")) == F.col("turns"), F.col("whole")).otherwise(wrong)
    return got.select("conv_id", "turns", formatted.alias("formatted"))


def loss_text(turns: Column) -> Column:
    return F.array_join(F.transform(F.filter(turns, lambda x: x["role"] == "assistant"), lambda x: x["text"]), "")


def read_back(formatted: DataFrame) -> DataFrame:
    """The digest columns, out of the formatted string alone."""
    back = formatted.select("conv_id", "formatted", parse(F.col("formatted")).alias("back"))
    back = back.withColumn("loss", loss_text(F.col("back")))
    joined = F.array_join(F.transform("back", lambda x: F.concat(x["role"], F.lit("\n"), x["text"], F.lit("\n"))), "")
    return back.select(
        "conv_id", F.size("back").cast("long").alias("n_turns"), F.sha2(joined.cast("binary"), 256).alias("turns_sha256"),
        F.length("loss").cast("long").alias("loss_chars"), F.sha2(F.col("loss").cast("binary"), 256).alias("loss_sha256"), F.length("formatted").cast("long").alias("formatted_chars"),
    )


ORACLE = r"""
WITH c AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok' UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'),
e AS (SELECT *, CASE WHEN contains(text, chr(10) || '</turn>' || chr(10)) OR starts_with(text, '</turn>' || chr(10)) OR ends_with(text, chr(10) || '</turn>') OR text = '</turn>'
    OR regexp_matches(text, '\\(\\|###|</turn>)') THEN regexp_replace(text, '(\\|###|</turn>)', '\\\1', 'g') ELSE text END AS body FROM c)
SELECT conv_id, count(*)::BIGINT AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  coalesce(sum(length(text)) FILTER (role = 'assistant'), 0)::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
  sum(length(body) + length(role) + 4 + 2 + 9)::BIGINT AS formatted_chars
FROM e GROUP BY conv_id
"""
