"""Quotation linking in conversations; DataFrame functions only.

A line that begins with ``>`` marks is quoted, its level is their number. Runs of lines
of one level are passages. Reply lines (level 0) make a message's own text; that text,
its paragraphs and its lines are the units others may quote. Passages and units are
normalised (lower case, runs of white space as one blank) and hashed; a passage is joined
to the first message of its conversation with the unit, else (for passages of
``min_chars`` or more) to the first message of all with it. Units are reduced to that first
message before the join, so a very common line yields one row.

A message's parent is the original of its first linked level-1 passage. Parents come
earlier by (conversation, turn), so there are no cycles; roots are found by
pointer jumping. A thread is all messages with roots in one conversation, in
the order of (conversation, turn), in which replies follow what they answer.

Defined results: a null text has no lines; a message without conversation or turn never
links and has no thread; a message does not link to itself; repeated messages are
one for linking and keep all their rows; an empty table gives an empty result; other
columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.ordering import running_totals
from ..plans.stages import cut, drop

MARKS = r"^[ \t]*(>[ \t]*)+"


def normal(text: Column) -> Column:
    return F.trim(F.regexp_replace(F.lower(text), r"\s+", " "))


def _let(value: Column, body) -> Column:
    """``body(value)`` with the value worked out once a row, however often the body uses it."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def parse(df: DataFrame, conv_col: str = "conv_id", turn_col: str = "turn", text_col: str = "text") -> DataFrame:
    """Each message's reply text, its units and its passages (level, normalised text)."""

    def of_runs(lines: Column, levels: Column, starts: Column) -> Column:
        def run(s: Column, j: Column) -> Column:
            end = F.coalesce(F.get(starts, j + 1), F.size(lines))
            bodies = F.transform(F.slice(lines, s + 1, end - s), lambda x: F.regexp_replace(x, MARKS, ""))
            return F.struct(F.get(levels, s).alias("level"), normal(F.array_join(bodies, "\n")).alias("text"))

        reply = F.filter(lines, lambda x, i: F.get(levels, i) == 0)
        return F.struct(
            F.filter(F.transform(starts, run), lambda r: r["text"] != "").alias("runs"),
            reply.alias("lines"),
            F.regexp_replace(F.array_join(reply, "\n"), r"^\s+|\s+$", "").alias("reply"),
            F.array_max(levels).alias("depth"),
        )

    def of_levels(lines: Column, levels: Column) -> Column:
        # a run ends where the level changes, and a run of reply lines also at a blank line
        def begins(i: Column) -> Column:
            blank = (F.get(levels, i) == 0) & ((F.trim(F.get(lines, i)) == "") | (F.trim(F.get(lines, i - 1)) == ""))
            return (i == 0) | (F.get(levels, i) != F.get(levels, i - 1)) | blank

        return _let(F.filter(F.sequence(F.lit(0), F.size(lines) - 1), begins), lambda starts: of_runs(lines, levels, starts))

    def finish(p: Column) -> Column:
        units = F.array_union(F.transform(F.filter(p["runs"], lambda r: r["level"] == 0), lambda r: r["text"]), F.transform(p["lines"], normal))
        units = F.filter(F.array_union(units, F.array(normal(p["reply"]))), lambda u: u != "")
        return F.struct(p["reply"].alias("reply"), F.transform(units, lambda u: F.xxhash64(u)).alias("units"), F.filter(p["runs"], lambda r: r["level"] > 0).alias("passages"), p["depth"].alias("depth"))

    level = lambda x: F.length(F.regexp_replace(F.regexp_extract(x, MARKS, 0), r"[ \t]", ""))
    lines = F.split(F.coalesce(F.col(text_col), F.lit("")), "\n", -1)
    parsed = _let(_let(lines, lambda x: _let(F.transform(x, level), lambda levels: of_levels(x, levels))), finish)
    out = df.select(F.col(conv_col).alias("_conv"), F.col(turn_col).alias("_turn"), parsed.alias("_p"))
    return out.select("_conv", "_turn", F.col("_p.reply").alias("_reply"), F.col("_p.units").alias("_units"), F.col("_p.passages").alias("_passages"), F.col("_p.depth").alias("_depth"))


def link_quotations(df: DataFrame, min_chars: int = 20, conv_col: str = "conv_id", turn_col: str = "turn", text_col: str = "text", role_col: str = "role") -> DataFrame:
    """One row a message: own text, counts of quotations, parent, thread and position in it."""
    parsed = parse(df, conv_col, turn_col, text_col)
    keyed = parsed.where("_conv is not null and _turn is not null")
    passages = cut(
        keyed.where(F.size("_passages") > 0)
        .select("_conv", "_turn", F.posexplode("_passages").alias("_at", "_p"))
        .select("_conv", "_turn", "_at", F.col("_p.level").alias("_level"), F.xxhash64("_p.text").alias("_hash"), F.length("_p.text").alias("_chars"))
        .distinct(),
        "passages",
    )
    wanted = passages.select("_hash").distinct()
    units = keyed.select("_conv", "_turn", F.explode(F.array_distinct("_units")).alias("_hash")).join(wanted, "_hash", "left_semi")
    units = cut(units.groupBy("_hash", "_conv").agg(F.min("_turn").alias("_near")), "units")
    first = units.groupBy("_hash").agg(F.min(F.struct("_conv", "_near")).alias("_far"))
    linked = passages.join(units, ["_hash", "_conv"], "left").join(first, "_hash", "left")
    same = F.col("_near") < F.col("_turn")
    other = (F.col("_far._conv") < F.col("_conv")) & (F.col("_chars") >= min_chars)
    target = F.when(same, F.struct(F.col("_conv").alias("c"), F.col("_near").alias("t"))).when(other, F.struct(F.col("_far._conv").alias("c"), F.col("_far._near").alias("t")))
    linked = linked.withColumn("_to", target)
    told = linked.groupBy("_conv", "_turn").agg(
        F.count("*").alias("_quoted"),
        F.count("_to").alias("_linked"),
        F.min(F.when((F.col("_level") == 1) & F.col("_to").isNotNull(), F.struct("_at", "_to")))["_to"].alias("_parent"),
    )
    told = cut(told, "told")
    roots = _roots(told.where("_parent is not null").select(F.struct(F.col("_conv").alias("c"), F.col("_turn").alias("t")).alias("m"), F.col("_parent").alias("p")))
    told = told.join(roots.select(F.col("m.c").alias("_conv"), F.col("m.t").alias("_turn"), F.col("root.c").alias("_root"), "hops"), ["_conv", "_turn"], "left")
    rows = df.select(F.col(conv_col).alias("_conv"), F.col(turn_col).alias("_turn"), F.col(role_col).alias("_role"), F.col(text_col).alias("_text"))
    out = _with_role(rows).join(told, ["_conv", "_turn"], "left").withColumn("_thread", F.coalesce("_root", "_conv")).withColumn("_one", F.lit(1).cast("long"))
    out = out.select("_thread", "_conv", "_turn", "_role", "_reply", "_depth", "_quoted", "_linked", "_parent", "hops", "_one")
    out = running_totals(out, ["_thread", "_conv", "_turn", "_role"], {"_rank": "_one"}, label="threads")
    starts = out.groupBy("_thread").agg(F.min("_rank").alias("_zero"))
    out = out.join(starts, "_thread", "left")
    return out.select(
        F.col("_conv").alias(conv_col),
        F.col("_turn").alias(turn_col),
        F.col("_role").alias("role"),
        F.col("_reply").alias("reply_text"),
        F.col("_depth").cast("long").alias("quote_depth"),
        F.coalesce("_quoted", F.lit(0)).cast("long").alias("n_quotes"),
        F.coalesce("_linked", F.lit(0)).cast("long").alias("n_linked"),
        F.col("_parent.c").alias("parent_conv"),
        F.col("_parent.t").alias("parent_turn"),
        F.col("_thread").alias("thread_id"),
        F.coalesce("hops", F.lit(0)).cast("long").alias("reply_depth"),
        F.when(F.col("_thread").isNotNull(), F.col("_rank") - F.col("_zero")).alias("position"),
    )


def _with_role(rows: DataFrame) -> DataFrame:
    """Parsed messages with their role; the role rides along in the conversation key."""
    packed = rows.select(F.struct("_conv", "_role").alias("_conv"), "_turn", "_text")
    parsed = parse(packed, "_conv", "_turn", "_text")
    return parsed.select(F.col("_conv._conv").alias("_conv"), "_turn", F.col("_conv._role").alias("_role"), "_reply", "_depth")


def _roots(parents: DataFrame) -> DataFrame:
    """``(m, p)`` -> ``(m, root, hops)`` by doubling the reach of each pointer."""
    now = cut(parents.select("m", F.col("p").alias("root"), F.lit(1).cast("long").alias("hops")), "roots")
    while True:
        far = now.select(F.col("m").alias("root"), F.col("root").alias("_next"), F.col("hops").alias("_more"))
        new = cut(now.join(far, "root", "left").select("m", F.coalesce("_next", "root").alias("root"), (F.col("hops") + F.coalesce("_more", F.lit(0))).alias("hops"), F.col("_next").isNotNull().alias("_moved")), "roots")
        moved = new.where("_moved").limit(1).count()
        drop(now)
        now = new
        if not moved:
            return now
