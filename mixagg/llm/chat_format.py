"""Chat formatting with Spark expressions only.

Turns of a conversation are collected as structs in blocks, sorted, merged where neighbours share a role and
joined to one string.  Control strings inside texts and roles are escaped reversibly, so the output can be
parsed back.  Defined cases: a null or empty text is an empty turn; a null role is the empty role; turns with
equal numbers are ordered by role, then text (nulls first); repeated rows stay as they are; extra columns are
ignored; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# The template's control strings.
START, END, NEXT = "<|im_start|>", "<|im_end|>", "<|im_next|>"

TURNS_PER_BLOCK = 512


def escape(c: Column) -> Column:
    """A backslash goes into every ``<|``, behind those that are there already."""
    return F.regexp_replace(c, r"<(\\*)\|", r"<$1\\|")


def unescape(c: Column) -> Column:
    return F.regexp_replace(c, r"<\\(\\*)\|", r"<$1|")


def _escape_role(c: Column) -> Column:
    return escape(F.replace(F.replace(c, F.lit("\\"), F.lit("\\\\")), F.lit("\n"), F.lit("\\n")))


def _unescape_role(c: Column) -> Column:
    parts = F.split(unescape(c), r"\\\\", -1)  # on doubled backslashes; what is left are newlines' marks
    return F.array_join(F.transform(parts, lambda p: F.replace(p, F.lit("\\n"), F.lit("\n"))), "\\")


def let(value: Column, body) -> Column:
    """``body`` of a value that is computed once; an expression named twice inside a lambda is run twice."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def run_starts(turns: Column) -> Column:
    """1-based positions at which the role changes."""
    return F.filter(F.sequence(F.lit(1), F.size(turns)), lambda i: (i == 1) | (F.get(turns, i - 1)["role"] != F.get(turns, i - 2)["role"]))


def merged_turns(turns: Column, heads: Column) -> Column:
    """Neighbouring turns of one role become one struct of the role and its texts' array."""

    def run(i: Column, k: Column) -> Column:
        part = F.slice(turns, i, F.coalesce(F.get(heads, k + 1), F.size(turns) + 1) - i)
        return let(part, lambda p: F.struct(F.get(p, F.lit(0))["role"].alias("role"), F.transform(p, lambda t: t["text"]).alias("texts")))

    return F.transform(heads, run)


def format_conversations(
    df: DataFrame, conv: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text",
    learn: tuple[str, ...] = ("assistant",), block: int = TURNS_PER_BLOCK,
) -> DataFrame:
    """One row per conversation: ``conv_id``, ``formatted`` and ``segments``.

    ``segments`` are structs (text, loss) whose texts in order make ``formatted``; the loss mask covers each
    text of a role in ``learn``, escaped, without headers and marks.  A long conversation is first collected
    in blocks of ``block`` turn numbers, so no task sorts it row by row.
    """
    rows = df.select(
        F.col(conv).alias("conv_id"),
        F.floor(F.col(turn) / block).alias("part"),
        F.col(turn).alias("turn"),
        _escape_role(F.coalesce(F.col(role).cast("string"), F.lit(""))).alias("role"),
        escape(F.coalesce(F.col(text), F.lit(""))).alias("text"),
    )
    blocks = rows.groupBy("conv_id", "part").agg(F.sort_array(F.collect_list(F.struct("turn", "role", "text"))).alias("turns"))
    whole = blocks.groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("part", "turns"))).alias("blocks"))
    # turns and heads stay columns of their own: each is read many times
    turns = whole.select("conv_id", F.flatten(F.transform("blocks", lambda b: b["turns"])).alias("turns"))
    heads = turns.withColumn("heads", run_starts(F.col("turns")))
    merged = heads.select("conv_id", merged_turns(F.col("turns"), F.col("heads")).alias("merged"))

    def pieces(m: Column) -> Column:
        loss = m["role"].isin(*learn)
        texts = F.flatten(F.transform(m["texts"], lambda t, i: F.when(
            i == 0, F.array(F.struct(t.alias("text"), loss.alias("loss")))
        ).otherwise(F.array(F.struct(F.lit(NEXT).alias("text"), F.lit(False).alias("loss")), F.struct(t.alias("text"), loss.alias("loss"))))))
        head = F.array(F.struct(F.concat(F.lit(START), m["role"], F.lit("\n")).alias("text"), F.lit(False).alias("loss")))
        tail = F.array(F.struct(F.lit(END + "\n").alias("text"), F.lit(False).alias("loss")))
        return F.concat(head, texts, tail)

    out = merged.select("conv_id", F.flatten(F.transform("merged", pieces)).alias("segments"))
    return out.select("conv_id", F.array_join(F.transform("segments", lambda s: s["text"]), "").alias("formatted"), "segments")


def parse_formatted(formatted: Column) -> Column:
    """The turns of a formatted conversation: an array of structs (role, text), as they were before merging."""
    pieces = F.slice(F.split(formatted, r"<\|im_start\|>", -1), 2, 1 << 30)

    def turns(p: Column) -> Column:
        def of(role: Column) -> Column:
            body = F.substr(p, F.length(role) + 2, F.length(p) - F.length(role) - 1 - len(END) - 1)
            return let(_unescape_role(role), lambda said: F.transform(F.split(body, r"<\|im_next\|>", -1), lambda t: F.struct(said.alias("role"), unescape(t).alias("text"))))

        return let(F.substring_index(p, "\n", 1), of)

    return F.flatten(F.transform(pieces, turns))


def masked_text(segments: Column) -> Column:
    """All text under the loss mask, unescaped, in order."""
    return F.array_join(F.transform(F.filter(segments, lambda s: s["loss"]), lambda s: unescape(s["text"])), "")


def digests(out: DataFrame) -> DataFrame:
    """What the formatted output says when it is read back."""
    parsed = out.select("conv_id", "formatted", parse_formatted(F.col("formatted")).alias("turns"), masked_text(F.col("segments")).alias("loss"))
    said = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return parsed.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(said.cast("binary"), 256).alias("turns_sha256"),
        F.length("loss").cast("long").alias("loss_chars"),
        F.sha2(F.col("loss").cast("binary"), 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
    )
