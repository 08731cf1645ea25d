"""Conversations in reply order, linked by their quotations, in DataFrame operations only.

A line that begins with ">" marks quotes what was said before; the number of marks is the level.
A message's own lines (level 0) are its text; its lines of level 1 and deeper, in blocks of one level,
are quotations. Passages are hashed after normalising: a message offers the hash of its whole text, of
its paragraphs and of its lines; a quoted block asks for its hash, and for the hashes of its lines.
Within a conversation the quotation of the lowest level that is found links the message to the latest
earlier message offering it: its parent. Without one, the message answers the one before it.

Messages between two linked ones form a run with the linked one that leads it. Runs are a tree: a run
hangs on the message that its head answers. Replies come right behind what they answer, so a message's
position is its place in its run, moved by the sizes of the runs that hang before it. Sizes, positions
and depths go up and down the tree by pointer doubling: rounds grow with the logarithm of the depth,
rows never exceed the number of runs.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from flowregions.llm.common import cut, table

#: Single lines and paragraphs shorter than this link nothing ("yes", "ok"); whole messages and whole quoted blocks do at any length.
LEAST_CHARS = 12
#: Marks between blocks and behind their level; in texts they count as blanks.
BLOCK, LEVEL = "\u0001", "\u0002"


def level(line: Column) -> Column:
    """Number of ">" marks at a line's beginning, blanks between allowed."""
    return F.length(F.regexp_replace(F.regexp_extract(line, r"^((?:[ \t]*>)*)", 1), r"[^>]", ""))


def bare(line: Column) -> Column:
    return F.regexp_replace(line, r"^(?:[ \t]*>)+[ \t]?", "")


def normal(text: Column) -> Column:
    return F.trim(F.regexp_replace(F.lower(text), r"[\x00-\x20]+", " "))


def parsed(messages: DataFrame) -> DataFrame:
    """Adds ``own`` (text without quotations), ``offers`` (hashes) and ``asks`` (structs of level, hash) to rows with ``text``."""
    line = F.transform(F.split(F.coalesce("text", F.lit("")), "\r?\n"), lambda x: F.struct(level(x).alias("level"), bare(x).alias("x")))
    rows = messages.withColumn("lines", line)
    own = F.array_join(F.transform(F.filter("lines", lambda s: s["level"] == 0), lambda s: s["x"]), "\n")
    rows = rows.withColumn("own", F.trim(F.regexp_replace(own, r"\n{3,}", "\n\n")))
    # the lines of one level in a row become one block: a mark where the level changes, then one split
    clean = lambda x: F.translate(x, BLOCK + LEVEL, "  ")
    begins = lambda s, i: ~s["level"].eqNullSafe(F.get("lines", i - 1)["level"])
    marked = F.transform("lines", lambda s, i: F.when(begins(s, i), F.concat(F.lit(BLOCK), s["level"].cast("string"), F.lit(LEVEL), clean(s["x"]))).otherwise(F.concat(F.lit("\n"), clean(s["x"]))))
    blocks = F.transform(F.filter(F.split(F.array_join(marked, ""), BLOCK), lambda b: (b != "") & ~b.startswith("0" + LEVEL)), lambda b: F.struct(F.split(b, LEVEL, 2)[0].cast("int").alias("level"), F.split(b, LEVEL, 2)[1].alias("x")))
    none = F.array().cast("array<struct<level:int,x:string>>")
    rows = rows.withColumn("blocks", F.when(F.exists("lines", lambda s: s["level"] > 0), blocks).otherwise(none))
    some = lambda xs, least: F.filter(F.transform(xs, normal), lambda x: F.length(x) >= least)
    passages = lambda whole, *parts: F.array_distinct(F.concat(some(F.array(whole), 1), *[some(p, LEAST_CHARS) for p in parts]))
    offers = passages(F.col("own"), F.split("own", r"\n[ \t]*\n"), F.split("own", "\n"))
    asks = F.flatten(F.transform("blocks", lambda b: F.transform(passages(b["x"], F.split(b["x"], "\n")), lambda x: F.struct(b["level"].alias("level"), F.xxhash64(x).alias("hash")))))
    return rows.withColumn("offers", F.transform(offers, lambda x: F.xxhash64(x))).withColumn("asks", asks).drop("lines", "blocks")


def parents(rows: DataFrame) -> DataFrame:
    """(conv, seq, parent struct<seq, turn>) of messages whose quotations are found. Only quoting messages and hashes they ask for are joined."""
    asked = cut(rows.filter(F.size("asks") > 0).select("conv", "seq", F.explode("asks").alias("ask")).select("conv", "seq", F.col("ask.level").alias("level"), F.col("ask.hash").alias("hash")).distinct())
    # the latest offer before the asking message, per (conversation, hash): offers and asks in one order, nothing is paired
    place = F.struct("seq", "turn")
    offered = rows.select("conv", "seq", place.alias("offer"), F.explode("offers").alias("hash")).join(asked.select("conv", "hash").distinct(), ["conv", "hash"], "left_semi")
    events = offered.select("conv", "hash", "seq", F.lit(None).cast("int").alias("level"), "offer").unionByName(asked.select("conv", "hash", "seq", "level", F.lit(None).cast("struct<seq:int,turn:bigint>").alias("offer")))
    before = Window.partitionBy("conv", "hash").orderBy("seq").rangeBetween(Window.unboundedPreceding, -1)
    found = events.withColumn("parent", F.max("offer").over(before)).filter(F.col("level").isNotNull() & F.col("parent").isNotNull())
    best = F.min_by("parent", F.struct("level", -F.col("parent.seq")))
    return found.groupBy("conv", "seq").agg(best.alias("parent"))


def grown(tree: DataFrame) -> DataFrame:
    """(conv, run, up, at, size): ``tree`` (conv, run, up, at, len) with the messages of each run and of all runs below it."""
    state = cut(tree.select("conv", "run", "up", "at", F.col("up").alias("anc"), F.col("len").alias("size")))
    while not state.filter("anc is not null").isEmpty():
        below = state.filter("anc is not null").groupBy("conv", F.col("anc").alias("run")).agg(F.sum("size").alias("more"))
        above = state.select("conv", F.col("run").alias("anc"), F.col("anc").alias("next"))
        step = state.join(below, ["conv", "run"], "left").join(above, ["conv", "anc"], "left")
        state = cut(step.select("conv", "run", "up", "at", F.col("next").alias("anc"), (F.col("size") + F.coalesce("more", F.lit(0))).alias("size")))
    return state.drop("anc")


def placed(tree: DataFrame) -> DataFrame:
    """(conv, run, position, depth) of the runs' heads from ``grown`` runs: 1 for a conversation's first run, others behind what they answer and earlier replies to it."""
    earlier = F.coalesce(F.sum("size").over(Window.partitionBy("conv", "up").orderBy("at", "run").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    inner = tree.filter("up is not null").select("conv", "run", F.col("up").alias("anc"), (F.col("at") - F.col("up") + 1 + earlier).alias("moved"), F.lit(1).alias("depth"))
    root = tree.filter("up is null").select("conv", "run", F.lit(None).cast("int").alias("anc"), F.lit(0).cast("long").alias("moved"), F.lit(0).alias("depth"))
    state = cut(inner.unionByName(root))
    while not state.filter("anc is not null").isEmpty():
        above = state.select("conv", F.col("run").alias("anc"), F.col("anc").alias("next"), F.col("moved").alias("m"), F.col("depth").alias("d"))
        step = state.join(above, ["conv", "anc"], "left")
        state = cut(step.select("conv", "run", F.col("next").alias("anc"), (F.col("moved") + F.coalesce("m", F.lit(0))).alias("moved"), (F.col("depth") + F.coalesce("d", F.lit(0))).alias("depth")))
    return state.select("conv", "run", (F.col("moved") + 1).alias("position"), "depth")


def conversations(messages: DataFrame, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """(conv_id, turn, role, text, parent, thread, depth, position) of every message: quotations removed, in reply order by position (from 1).

    ``parent``: the turn answered, null for a conversation's first message; ``thread``: the turn of that
    first message; messages that only follow the one before stay in its run at its depth. Null and empty
    texts have an empty text and link nothing. Messages without a conversation or turn take no part.
    Repeated rows count once; different messages of one turn all stay, in order of (role, text), nulls
    first. Very long texts are parsed in time linear in their lines. Other columns are neither read nor
    returned, so names cannot clash. An empty table gives no rows.
    """
    rows = messages.select(messages[conv_col].cast("long").alias("conv"), messages[turn_col].cast("long").alias("turn"), messages[role_col].cast("string").alias("role"), messages[text_col].cast("string").alias("text"))
    rows = rows.filter("conv is not null and turn is not null").distinct()
    rows = rows.withColumn("seq", F.row_number().over(Window.partitionBy("conv").orderBy("turn", "role", "text")))
    rows = table(parsed(rows).drop("text"))
    upto = Window.partitionBy("conv").orderBy("seq")
    told = rows.select("conv", "seq", "turn").join(parents(rows), ["conv", "seq"], "left")
    # a message that quotes nothing found belongs to the one before; runs of such hang on the run's first message
    head = F.last(F.when(F.col("parent").isNotNull(), F.col("seq")), ignorenulls=True).over(upto)
    told = cut(told.select("conv", "seq", "turn", "parent", F.coalesce(head, F.lit(1)).alias("run"), F.first("turn").over(upto).alias("first"), F.lag("turn").over(upto).alias("before")))
    length = told.groupBy("conv", "run").agg(F.count("*").alias("len"), F.max(F.when(F.col("seq") == F.col("run"), F.col("parent.seq"))).alias("at"))
    tree = grown(length.join(told.select("conv", F.col("seq").alias("at"), F.col("run").alias("up")), ["conv", "at"], "left"))
    hung = tree.filter("at is not null").groupBy("conv", F.col("at").alias("seq")).agg(F.sum("size").alias("hung"))
    inside = Window.partitionBy("conv", "run").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)
    every = told.join(hung, ["conv", "seq"], "left").withColumn("moved", F.coalesce(F.sum("hung").over(inside), F.lit(0))).join(placed(tree), ["conv", "run"])
    place = (F.col("position") + F.col("seq") - F.col("run") + F.col("moved")).cast("int")
    slim = every.select("conv", "seq", "first", F.coalesce("parent.turn", "before").alias("parent"), "depth", place.alias("position"))
    out = rows.select("conv", "seq", "turn", "role", "own").join(slim, ["conv", "seq"])
    return out.select(F.col("conv").alias(conv_col), F.col("turn").alias(turn_col), F.col("role").alias(role_col), F.col("own").alias(text_col), "parent", F.col("first").alias("thread"), "depth", "position")
