"""Chat formatting by quotation linking.

Lines of a message that start with `>` marks are quotes; their number of marks is the level. Consecutive lines of one level
are a passage: its lines, normalised and without blank ones, joined by spaces, so that it is the same however it is wrapped. Passages are
hashed, and a quoted one is joined to the first message of its conversation, before its own, that has it as a passage; failing that, as
whole lines of a passage; failing that, within one. A passage that nobody said as a whole is linked by its runs of lines, and stands for the message
of its longest run. A message answers the message that its outermost linked passage comes from. Messages
are then ordered by reply: each after the one it answers, answers in turn order, and formatted without quotes. A thread's order is a
walk that enters and leaves each of its messages; places along the walk come from steps that double in length, so rows are two
a message however deep the thread is.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from itertools import accumulate, groupby

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

MARKS = r"^(?:[ \t]*>)+[ \t]?"
#: Answers to one message are put in order within spans of so many turns, and the spans among themselves.
SPAN = 4096
#: First words (a power of two, at most this many) by which places that may hold a passage are found; the rest is compared there.
GRAM = 64
_MARKS, _BREAK = re.compile(MARKS), re.compile(r"\r?\n")
_SPACE = re.compile(r"\s+", re.ASCII)


def passages(text: str) -> list[tuple[int, int, list[str]]]:
    """First line, level and non-blank normal lines of each passage of a text; passages of blank lines are left out."""
    lines = []
    for at, line in enumerate(_BREAK.split(text)):
        marks = _MARKS.match(line)
        body = line[marks.end() :] if marks else line
        lines.append((marks[0].count(">") if marks else 0, at, _SPACE.sub(" ", body).strip(" ").lower()))
    out = []
    for level, run in groupby(lines, key=lambda x: x[0]):
        run = list(run)
        if said := [x for _, _, x in run if x]:
            out.append((run[0][1], level, said))
    return out


def _passages(messages: DataFrame) -> DataFrame:
    """A row for each passage of the conversations that quote: conv_id, turn, at, level, words, and the word that each line starts at, with the end."""
    quotes = F.exists(F.split("text", r"\r?\n"), lambda x: x.rlike(MARKS))
    slim = common.bounded(messages.where("text is not null").join(messages.where(quotes).select("conv_id").distinct(), "conv_id", "left_semi").select("conv_id", "turn", "text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo, hi in common.text_slices(batch):
                part = batch.slice(lo, hi - lo)
                found = [(i, *p) for i, t in enumerate(common.column(part, "text").to_pylist()) for p in passages(t)]
                rows = pa.array([f[0] for f in found], pa.int64())
                split = [[x.split(" ") for x in f[3]] for f in found]
                yield pa.RecordBatch.from_arrays(
                    [
                        common.column(part, "conv_id").take(rows),
                        common.column(part, "turn").take(rows),
                        pa.array([f[1] for f in found], pa.int64()),
                        pa.array([f[2] for f in found], pa.int64()),
                        pa.array([[w for x in lines for w in x] for lines in split], pa.list_(pa.string())),
                        pa.array([[0, *accumulate(map(len, lines))] for lines in split], pa.list_(pa.int32())),
                    ],
                    ["conv_id", "turn", "at", "level", "words", "bounds"],
                )

    kind = {c: slim.schema[c].dataType.simpleString() for c in ("conv_id", "turn")}
    return slim.mapInArrow(common.tidy(run), f"conv_id {kind['conv_id']}, turn {kind['turn']}, at long, level long, words array<string>, bounds array<int>")


def _hashes(words: Column) -> list[Column]:
    text = F.array_join(words, " ")
    return [F.xxhash64(text).alias("h"), F.md5(text).alias("m")]


def _within(said: DataFrame, wanted: DataFrame) -> DataFrame:
    """conv_id, text, and the first turns that say each wanted text (conv_id, text) as whole lines (`lined`) and in any place (`inside`)."""
    parts = wanted.distinct().withColumn("w", F.split("text", " ")).withColumn("size", F.size("w"))
    parts = parts.withColumn("k", F.least(F.pow(2, F.floor(F.log2("size"))), F.lit(GRAM)).cast("int"))
    parts = parts.select("conv_id", "text", "size", "k", F.xxhash64(F.slice("w", F.lit(1), F.col("k"))).alias("g"))
    places = F.transform(F.sequence(F.lit(0), F.size("words") - F.col("k")), lambda i: F.xxhash64(F.slice(F.col("words"), i + 1, F.col("k"))))
    own = said.join(parts.select("conv_id", "k").distinct(), "conv_id").where(F.size("words") >= F.col("k"))
    own = own.select("conv_id", "oid", "k", F.size("words").alias("all"), F.posexplode(places).alias("pos", "g"))
    met = own.join(parts, ["conv_id", "k", "g"]).where("pos + size <= all").select("conv_id", "oid", "pos", "size", "text")
    met = met.join(said, ["conv_id", "oid"]).where(F.array_join(F.slice("words", F.col("pos") + 1, F.col("size")), " ") == F.col("text"))
    lined = F.array_contains("bounds", F.col("pos")) & F.array_contains("bounds", F.col("pos") + F.col("size"))
    return met.groupBy("conv_id", "text").agg(F.min(F.when(lined, F.col("origin"))).alias("lined"), F.min("origin").alias("inside"))


def _before(*turns: str) -> Column:
    """The first of the turns that lies before the message's own."""
    return F.coalesce(*(F.when(F.col(t) < F.col("turn"), F.col(t)) for t in turns))


def _find(said: DataFrame, whole: DataFrame, rows: DataFrame) -> DataFrame:
    """`rows` (conv_id, turn, text, ...) with the earlier turn that says the text, or null, as `origin`."""
    found = _within(said, rows.select("conv_id", "text"))
    keyed = rows.withColumn("h", F.xxhash64("text")).withColumn("m", F.md5("text"))
    met = keyed.join(whole, ["conv_id", "h", "m"], "left").join(found, ["conv_id", "text"], "left")
    return met.withColumn("origin", _before("whole", "lined", "inside")).drop("h", "m", "whole", "lined", "inside", "text")


def _runs(said: DataFrame, whole: DataFrame, rest: DataFrame) -> DataFrame:
    """Of passages that nobody said as a whole: lines linked, and the turn of the longest linked run of lines.

    A run can only be said if a shorter one from the same line is, so the longest run from each line is found by halving steps: rounds follow the
    logarithm of the lines of the longest passage.
    """
    keys = ["conv_id", "turn", "at", "pid"]
    lines = rest.select(*keys, F.explode(F.sequence(F.lit(0), F.size("bounds") - 2)).alias("s"))
    state = common.materialise(lines.withColumn("r", F.lit(0)).withColumn("origin", F.lit(None).cast(rest.schema["turn"].dataType)), "runs")
    step = 1 << (int(rest.agg(F.max(F.size("bounds") - 1)).first()[0]).bit_length() - 1)
    end = lambda n: F.get("bounds", F.col("s") + F.col("r") + n)
    start = F.get("bounds", F.col("s"))
    while step:
        texts = state.join(rest, keys).where(F.col("s") + F.col("r") + step < F.size("bounds"))
        texts = texts.select(*keys, "s", F.array_join(F.slice("words", start + 1, end(step) - start), " ").alias("text"))
        found = _find(said, whole, texts).where("origin is not null").withColumnRenamed("origin", "new")
        old, state = state, common.materialise(
            state.join(found, [*keys, "s"], "left").select(*keys, "s", F.when(F.col("new").isNotNull(), F.col("r") + step).otherwise(F.col("r")).alias("r"), F.coalesce("new", "origin").alias("origin")), "runs"
        )
        common.discard(old)
        step //= 2
    long = state.where("r > 0").join(rest.select(*keys, "bounds"), keys).select(*keys, F.struct((end(0) - start).alias("n"), (-F.col("s")).alias("s"), "origin").alias("run"))
    return long.groupBy(*keys).agg(F.count("*").alias("lines"), F.max("run").alias("run")).select(*keys, "lines", F.col("run.origin").alias("origin"))


def _links(messages: DataFrame) -> DataFrame:
    """conv_id, turn, quoted and linked lines of each message that quotes, and the turn it answers."""
    every = common.materialise(_passages(messages), "passages")
    said = every.where("level = 0").groupBy("conv_id", "words", "bounds").agg(F.min("turn").alias("origin"))
    said = said.withColumn("oid", F.md5(F.concat_ws("/", F.array_join("words", " "), F.array_join(F.transform("bounds", lambda x: x.cast("string")), " "))))
    whole = said.groupBy("conv_id", *_hashes(F.col("words"))).agg(F.min("origin").alias("whole"))
    quoted = every.where("level > 0").groupBy("conv_id", "turn", "at", "level", "words", "bounds").agg(F.count("*").alias("copies"))
    quoted = quoted.withColumn("text", F.array_join("words", " ")).select("*", *_hashes(F.col("words"))).withColumn("size", F.size("bounds") - 1).withColumn("pid", F.md5(F.concat_ws("/", "level", "m", F.array_join(F.transform("bounds", lambda x: x.cast("string")), " "))))
    met = common.materialise(quoted.join(whole, ["conv_id", "h", "m"], "left").withColumn("origin", _before("whole")).drop("h", "m", "whole"), "quoted")
    keys = ["conv_id", "turn", "at", "pid"]
    done = met.where("origin is not null").select(*keys, F.col("size").alias("lines"), "origin", F.lit(0).alias("broken"))
    rest = met.where("origin is null").drop("origin")
    if not rest.isEmpty():
        tried = common.materialise(_find(said, whole, rest), "tried")
        done = done.union(tried.where("origin is not null").select(*keys, F.col("size").alias("lines"), "origin", F.lit(0)))
        rest = tried.where("origin is null and size > 1").drop("origin")
        if not rest.isEmpty():
            done = done.union(_runs(said, whole, rest.select(*keys, "words", "bounds")).select(*keys, "lines", "origin", F.lit(1)))
    return met.drop("origin").join(done, keys, "left").groupBy("conv_id", "turn").agg(
        F.sum(F.col("copies") * F.col("size")).alias("n_quoted"),
        F.sum(F.col("copies") * F.coalesce("lines", F.lit(0))).alias("n_linked"),
        F.min(F.when(F.col("origin").isNotNull(), F.struct("level", "broken", "at", "origin"))).alias("first"),
    ).select("conv_id", "turn", "n_quoted", "n_linked", F.col("first.origin").alias("parent"))


def _walk(links: DataFrame) -> DataFrame:
    """The walk through every thread: an element (conv_id, turn, out) for entering and for leaving a message, and the element after it.

    A thread is a message that others answer, with its answers and theirs.
    """
    kids = links.where("parent is not null").select("conv_id", "turn", "parent")
    spans = kids.withColumn("b", F.floor(F.col("turn") / SPAN))
    near = spans.withColumn("near", F.lead("turn").over(Window.partitionBy("conv_id", "parent", "b").orderBy("turn")))
    heads = spans.groupBy("conv_id", "parent", "b").agg(F.min("turn").alias("head"))
    heads = heads.withColumn("far", F.lead("head").over(Window.partitionBy("conv_id", "parent").orderBy("b"))).drop("head")
    kids = near.join(heads, ["conv_id", "parent", "b"]).select("conv_id", "turn", "parent", F.coalesce("near", "far").alias("sibling"))
    first = kids.groupBy("conv_id", "parent").agg(F.min("turn").alias("child"))
    nodes = kids.select("conv_id", "turn").union(first.select("conv_id", F.col("parent").alias("turn"))).distinct()
    nodes = nodes.join(kids, ["conv_id", "turn"], "left").join(first.withColumnRenamed("parent", "turn"), ["conv_id", "turn"], "left")
    enter = nodes.select("conv_id", "turn", F.lit(False).alias("out"), F.coalesce("child", "turn").alias("next"), F.col("child").isNull().alias("next_out"))
    leave = nodes.select("conv_id", "turn", F.lit(True), F.coalesce("sibling", "parent"), F.col("sibling").isNull())
    return enter.union(leave)


def _order(links: DataFrame) -> DataFrame:
    """conv_id, turn, root_turn, position and depth of each message of a thread.

    Each element adds up what lies between it and the element it points to; elements point twice as far each round, so
    rounds follow the logarithm of the longest thread.
    """
    one = F.when(F.col("out"), 0).otherwise(1).cast("long")
    step = F.when(F.col("out"), -1).otherwise(1).cast("long")
    walk = common.materialise(_walk(links).select("*", one.alias("entered"), step.alias("level"), F.col("turn").alias("last")), "walk")
    while not walk.where("next is not null").isEmpty():
        ahead = walk.select("conv_id", F.col("turn").alias("next"), F.col("out").alias("next_out"), F.col("next").alias("far"), F.col("next_out").alias("far_out"), *(F.col(c).alias(f"more_{c}") for c in ("entered", "level", "last")))
        met = walk.join(ahead, ["conv_id", "next", "next_out"], "left")
        new = met.select("conv_id", "turn", "out", F.col("far").alias("next"), F.col("far_out").alias("next_out"), *((F.col(c) + F.coalesce(f"more_{c}", F.lit(0))).alias(c) for c in ("entered", "level")), F.coalesce("more_last", "last").alias("last"))
        old, walk = walk, common.materialise(new, "walk")
        common.discard(old)
    # what is left of a walk from a message on: it ends at the root, and leaves as many messages unentered as lie above
    ends = walk.where("not out").select("conv_id", "turn", F.col("last").alias("root_turn"), "entered", (-F.col("level")).alias("depth"))
    whole = ends.where("turn = root_turn").select("conv_id", "root_turn", F.col("entered").alias("all"))
    return ends.join(whole, ["conv_id", "root_turn"]).select("conv_id", "turn", "root_turn", (F.col("all") - F.col("entered")).alias("position"), "depth")


def format_chats(conversations: DataFrame) -> DataFrame:
    """A row for each message: conv_id, turn, role, parent_turn, depth, root_turn, position, n_quoted, n_linked, body, chat.

    Sorting by (conv_id, root_turn, position) reads a conversation in reply order: a thread is the message at its top (root_turn), which
    has position 0, and all that answer it or its answers, in the order of a walk that takes answers by turn; depth is the number of
    messages above. A quote can only come from an earlier turn of the same conversation; what is quoted from elsewhere counts
    as quoted, not linked. n_quoted and n_linked count non-blank lines. Body is the text without quoted lines, trimmed; chat puts the role before it. Null texts
    are empty, null roles `unknown`. Messages with a null conv_id or turn answer nothing. Rows that repeat a turn are
    each formatted, with the quotes of all of them counted together. A very long text is a slice of its own. Extra columns are
    ignored; an empty table stays empty. No conversation is gathered into one task.
    """
    slim = conversations.select("conv_id", "turn", "role", "text")
    links = common.materialise(_links(slim.where("conv_id is not null and turn is not null")), "links")
    body = F.array_join(F.filter(F.split(F.coalesce("text", F.lit("")), r"\r?\n"), lambda x: ~x.rlike(MARKS)), "\n")
    body = F.regexp_replace(body, r"^\s+|\s+$", "")
    out = slim.join(links, ["conv_id", "turn"], "left").join(_order(links), ["conv_id", "turn"], "left").withColumn("body", body)
    return out.select(
        "conv_id",
        "turn",
        "role",
        F.col("parent").alias("parent_turn"),
        F.coalesce("depth", F.lit(0)).cast("long").alias("depth"),
        F.coalesce("root_turn", "turn").alias("root_turn"),
        F.coalesce("position", F.lit(0)).cast("long").alias("position"),
        F.coalesce("n_quoted", F.lit(0)).cast("long").alias("n_quoted"),
        F.coalesce("n_linked", F.lit(0)).cast("long").alias("n_linked"),
        "body",
        F.concat(F.lit("<|"), F.coalesce("role", F.lit("unknown")), F.lit("|>\n"), F.col("body"), F.lit("\n")).alias("chat"),
    )


def op4_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    return format_chats(spark.read.parquet(f"{sf_dir}/conversations.parquet"))


#: Links single lines, so it says the same as the operator only where nothing is quoted, as in the given tables.
OP4_SQL = r"""
WITH RECURSIVE line AS (
  SELECT conv_id, turn, i AS pos, length(regexp_replace(regexp_extract(line, '^(?:[ \t]*>)+[ \t]?'), '[^>]', '', 'g')) AS level,
         lower(trim(regexp_replace(regexp_replace(line, '^(?:[ \t]*>)+[ \t]?', ''), '\s+', ' ', 'g'))) AS normal
  FROM (SELECT conv_id, turn, unnest(l) AS line, generate_subscripts(l, 1) AS i
        FROM (SELECT conv_id, turn, regexp_split_to_array(coalesce(text, ''), '\r?\n') AS l FROM conversations))
), said AS (
  SELECT conv_id, normal, min(turn) AS origin FROM line WHERE level = 0 AND normal <> '' GROUP BY ALL
), link AS (
  SELECT q.conv_id, q.turn, count(*) AS n_quoted, count(CASE WHEN origin < q.turn THEN 1 END) AS n_linked,
         arg_min(CASE WHEN origin < q.turn THEN origin END, CASE WHEN origin < q.turn THEN level * 1000000 + pos END) AS parent
  FROM line q LEFT JOIN said USING (conv_id, normal) WHERE q.level > 0 AND q.normal <> '' GROUP BY ALL
), up AS (
  SELECT conv_id, turn, turn AS head, [turn] AS path FROM conversations
  UNION
  SELECT u.conv_id, u.turn, l.parent, list_prepend(l.parent, path)
  FROM up u JOIN link l ON l.conv_id = u.conv_id AND l.turn = u.head WHERE l.parent IS NOT NULL
), top AS (
  SELECT conv_id, turn, arg_max(path, len(path)) AS path FROM up GROUP BY ALL
), o AS (
  SELECT conv_id, turn, len(path) - 1 AS depth, path[1] AS root_turn, row_number() OVER (PARTITION BY conv_id, path[1] ORDER BY path) - 1 AS position FROM top
), b AS (
  SELECT conv_id, turn, role, regexp_replace(array_to_string(list_filter(regexp_split_to_array(coalesce(text, ''), '\r?\n'), lambda x: NOT regexp_matches(x, '^(?:[ \t]*>)+[ \t]?')), chr(10)), '^\s+|\s+$', '', 'g') AS body
  FROM conversations
)
SELECT conv_id, turn, role, parent AS parent_turn, depth, root_turn, position, coalesce(n_quoted, 0)::BIGINT AS n_quoted, coalesce(n_linked, 0)::BIGINT AS n_linked,
       body, '<|' || coalesce(role, 'unknown') || '|>' || chr(10) || body || chr(10) AS chat
FROM b JOIN o USING (conv_id, turn) LEFT JOIN link USING (conv_id, turn)
"""
