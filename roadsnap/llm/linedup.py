"""Line dedup: a suffix array of line-ID sequences by prefix doubling, and removal of later copies of repeated runs.

Every line is its 128-bit hash.  Suffixes whose first line occurs once share nothing and are set aside; the others
are named.  Round j names the pairs (name of the first 2**j lines, path of the suffix that many lines on) in the
order of a global sort, so names keep the order of the suffixes; a *path* is the list of a suffix's names from its
first line's hash on, and ends with the round that told the suffix from all others.  Rounds go on until no name
repeats.  Paths sort as suffixes do, so sorting them is the suffix array (`suffix_array`), and two paths tell the
common prefix of their suffixes: the names they share, and then those of the suffixes that many lines on (`common`).
No step needs one machine to see a whole group: names are row numbers of a global sort.

All suffixes that share a prefix of d lines are one interval of the array, of depth d.  In every interval of depth
`min_lines` the suffix that comes first in the corpus is the source, and the others are later copies; so they are in an
interval of depth 1 whose line has at least `min_words` words.  A copy whose lines before it are a copy from there too
lies inside a longer run; what is left are maximal runs, as long as the common prefix with their source.
All lines of runs are deleted.

Order is (doc_id, line number), null doc_ids first.  A copy that overlaps the first one in the same text is left.
Defined results: a null text stays null; an empty text is one empty line; a text may become empty; rows that repeat
both doc_id and text count as one text (equal lines go from each); rows that share a doc_id only are
different texts, ordered by a hash of theirs; extra columns may have any name, but removed_lines and copied_from are replaced.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

from . import text as tk
from .store import drop, keep

MIN_LINES, MIN_WORDS = 2, 50
#: What stands for a null doc_id within this module.
NULL = -(1 << 63)
AT = ["did", "rid", "ln"]


def _ids():
    return F.coalesce("doc_id", F.lit(NULL)).alias("did"), F.xxhash64("doc_id", "text").alias("rid")


def line_ids(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """(did, rid, ln, rest, h1, h2, long) of every line of every distinct (doc_id, text).

    rest: lines from this one to the end; long: it has `min_words` words.
    """
    lines = docs.filter("text is not null").select(*_ids(), F.split("text", "\n", -1).alias("lines"))
    lines = lines.select("did", "rid", F.size("lines").alias("all"), F.posexplode("lines").alias("ln", "line"))
    words = F.when(F.char_length("line") >= 2 * min_words - 1, F.regexp_count("line", F.lit(r"[^\x00-\x20]+")) >= min_words).otherwise(False)
    return lines.select(*AT, (F.col("all") - F.col("ln")).alias("rest"), F.xxhash64("line").alias("h1"), F.xxhash64(F.lit(0x5BD1), "line").alias("h2"), words.alias("long"))


def _name(rows: DataFrame, keys: list[str], least: int) -> DataFrame:
    """Keys that occur at least so often, with order-preserving names and their number of occurrences."""
    often = rows.groupBy(*keys).agg(F.count("*").alias("n")).filter(F.col("n") >= least)
    return often.orderBy(*keys).withColumn("name", F.monotonically_increasing_id())


def suffixes(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """(did, rid, ln, rest, long, path) of all suffixes whose first line occurs more than once."""
    ids = keep(line_ids(docs, min_words).dropDuplicates(AT), "lines")
    names = _name(ids, ["h1", "h2"], 2)  # read once, so it is not kept
    # a broadcast of the names would change with the corpus; a row per line goes through one shuffle at every size
    named = keep(ids.join(names.select("h1", "h2", "name").hint("shuffle_hash"), ["h1", "h2"], "left"), "named")
    drop(ids)
    first = named.filter("name is not null").select(*AT, "rest", "long", F.array("h1", "h2").alias("path"))
    levels = [named.filter("name is not null").select(*AT, F.lit(0).alias("level"), "name")]
    active, texts, step = levels[0].drop("level"), named.withColumn("path", F.array("h1", "h2")).select(*AT, "path"), 1
    old = []
    while True:
        some = active.select("did", "rid").distinct()
        texts = keep(texts.join(some, ["did", "rid"], "left_semi"), "texts")  # no other text is looked up any more
        after = texts.select("did", "rid", (F.col("ln") - step).alias("ln"), F.col("path").alias("right"))
        pairs = keep(active.withColumnRenamed("name", "left").join(after, AT), "pairs")
        names = _name(pairs, ["left", "right"], 1)
        level = keep(pairs.join(names.hint("shuffle_hash"), ["left", "right"]).select(*AT, "name", "n"), "level")
        drop(pairs, *old)
        levels.append(level.select(*AT, F.lit(len(levels)).alias("level"), "name"))
        active, step = level.filter("n > 1").select(*AT, "name"), 2 * step
        if active.isEmpty():
            break
        old = [texts]
        texts = texts.join(level.select(*AT, "name"), AT, "left").select(*AT, F.when(F.col("name").isNull(), F.col("path")).otherwise(F.array_append("path", F.col("name"))).alias("path"))
    more = levels[1]
    for x in levels[2:]:
        more = more.unionByName(x)
    more = more.groupBy(*AT).agg(F.sort_array(F.collect_list(F.struct("level", "name"))).alias("more"))
    out = first.join(more, AT, "left").select(*AT, "rest", "long", F.when(F.col("more").isNull(), F.col("path")).otherwise(F.concat("path", F.transform("more", lambda x: x["name"]))).alias("path"))
    out = keep(out, "suffixes")
    drop(named, texts)
    return out


def common(pairs: DataFrame, paths: DataFrame) -> DataFrame:
    """Adds `lcp`, the number of lines that the suffixes (did, rid, ln) and (fdid, frid, fln) of each row share.

    Names shared beyond the two of the first line's hash stand for a power of two of lines, or for all that is left of
    both texts; then the suffixes that many lines on are compared, so there are at most as many rounds as there are
    bits in the longest common run.
    """
    done, names = None, pairs.columns
    live = pairs.withColumn("lcp", F.lit(0))
    a = paths.select("did", "rid", F.col("ln").alias("_at"), F.col("path").alias("_x"), F.col("rest").alias("_rest"))
    b = paths.select(F.col("did").alias("fdid"), F.col("rid").alias("frid"), F.col("ln").alias("_fat"), F.col("path").alias("_y"))
    while True:
        met = live.withColumn("_at", F.col("ln") + F.col("lcp")).withColumn("_fat", F.col("fln") + F.col("lcp"))
        met = met.join(a, ["did", "rid", "_at"], "left").join(b, ["fdid", "frid", "_fat"], "left")
        # rounds tell suffixes apart, so the shared part of two paths is where they first differ
        same = F.expr("cast(coalesce(array_position(zip_with(_x, _y, (x, y) -> coalesce(x = y, false)), false) - 1, -1) as int)")
        same = F.when(F.col("_x").isNull() | F.col("_y").isNull(), 0).when(same < 0, F.least(F.size("_x"), F.size("_y"))).otherwise(same)
        met = keep(met.withColumn("_c", same).select(*names, "lcp", "_c", "_rest"), "common")
        over = met.filter("_c < 2").select(*names, "lcp")
        done = over if done is None else done.unionByName(over)
        live = met.filter("_c >= 2").select(*names, (F.col("lcp") + F.expr("least(cast(pow(2, _c - 2) as int), _rest)")).alias("lcp"))
        if live.isEmpty():
            return done


def suffix_array(docs: DataFrame) -> DataFrame:
    """(doc_id, ln, rank, lcp): the order of the suffixes whose first line repeats; lcp is with the suffix before.

    Suffixes that are equal to their ends follow each other in the order of the corpus.
    """
    paths = suffixes(docs)
    ranked = keep(paths.orderBy("path", *AT).withColumn("place", F.monotonically_increasing_id()).withColumn("part", F.shiftright("place", 33)).select(*AT, "place", "part"), "ranked")
    # the row before a partition's first is the last of the partition before that has any: a row per partition
    ends = ranked.groupBy("part").agg(F.max_by(F.struct(*AT), "place").alias("end"), F.count("*").alias("n"))
    of_part = Window.orderBy("part")
    ends = ends.select("part", F.lag("end").over(of_part).alias("end"), (F.sum("n").over(of_part) - F.col("n")).alias("base"))
    inside = Window.partitionBy("part").orderBy("place")
    rows = ranked.withColumn("prev", F.lag(F.struct(*AT)).over(inside)).withColumn("turn", F.row_number().over(inside)).join(F.broadcast(ends), "part")
    before = F.coalesce("prev", "end")
    rows = keep(rows.select(*AT, (F.col("base") + F.col("turn") - 1).alias("rank"), before["did"].alias("fdid"), before["rid"].alias("frid"), before["ln"].alias("fln")), "array")
    out = common(rows.filter("fdid is not null"), paths).unionByName(rows.filter("fdid is null").withColumn("lcp", F.lit(0)))
    return out.select(F.nullif("did", F.lit(NULL)).alias("doc_id"), "ln", "rank", "lcp")


def _prefix(paths: DataFrame, lines: int) -> DataFrame:
    """(did, rid, ln, long, key): suffixes of at least so many lines, with what tells prefixes of that length apart."""
    level = lines.bit_length() - 1
    rest = lines - (1 << level)
    whole = paths.filter((F.size("path") >= level + 2) & (F.col("rest") >= 1 << level))
    head = whole.select(*AT, "long", F.slice("path", 1, level + 2).alias("key"))
    if rest == 0:
        return head
    # two prefixes of a power of two that overlap
    tail = whole.select("did", "rid", (F.col("ln") - rest).alias("ln"), F.slice("path", 1, level + 2).alias("tail"))
    return head.join(tail, AT).withColumn("key", F.concat("key", "tail")).drop("tail")


def repeated_runs(docs: DataFrame, min_lines: int = MIN_LINES, min_words: int | None = MIN_WORDS) -> DataFrame:
    """(did, rid, ln, lines, fdid, frid, fln): maximal runs that are later copies, and where they come first."""
    paths = suffixes(docs, min_words or MIN_WORDS)
    kinds = [(min_lines, _prefix(paths, min_lines))]
    if min_words and min_lines > 1:
        kinds.append((1, _prefix(paths, 1).filter("long")))
    found = None
    for depth, members in kinds:
        first = members.groupBy("key").agg(F.min(F.struct(*AT)).alias("f"), F.count("*").alias("n")).filter("n > 1")
        copy = members.join(first.select("key", "f"), "key").select(*AT, F.col("f.did").alias("fdid"), F.col("f.rid").alias("frid"), F.col("f.ln").alias("fln"))
        copy = copy.filter((F.col("did") != F.col("fdid")) | (F.col("rid") != F.col("frid")) | (F.col("ln") >= F.col("fln") + depth))
        found = copy if found is None else found.unionByName(copy)
    copies = keep(found.distinct(), "copies")
    inner = copies.select("did", "rid", (F.col("ln") + 1).alias("ln"), "fdid", "frid", (F.col("fln") + 1).alias("fln"))
    begin = copies.join(inner, copies.columns, "left_anti")
    return common(begin, paths).withColumnRenamed("lcp", "lines")


def dedup(docs: DataFrame, min_lines: int = MIN_LINES, min_words: int | None = MIN_WORDS) -> DataFrame:
    """`docs` without later copies of runs; also removed_lines and copied_from (doc_ids that have them first).

    A run is `min_lines` lines or more, or (unless `min_words` is None) one line of `min_words` words or more.
    """
    docs = tk.drop_columns(docs, ["removed_lines", "copied_from"])
    runs = repeated_runs(docs, min_lines, min_words)
    # overlapping runs are joined, so that a text is put together from what lies between, in one pass
    in_order = Window.partitionBy("did", "rid").orderBy("ln", "to")
    spans = runs.select("did", "rid", "ln", (F.col("ln") + F.col("lines")).alias("to"), "fdid").withColumn("before", F.max("to").over(in_order.rowsBetween(Window.unboundedPreceding, -1)))
    spans = spans.withColumn("gap", F.when(F.col("before").isNull() | (F.col("ln") >= F.col("before")), F.struct(F.coalesce("before", F.lit(0)).alias("at"), (F.col("ln") - F.coalesce("before", F.lit(0))).alias("n"))))
    gone = spans.groupBy("did", "rid").agg(
        F.sort_array(F.collect_list("gap")).alias("gaps"), F.max("to").alias("end"), F.sort_array(F.collect_set(F.nullif("fdid", F.lit(NULL)))).alias("source"))
    did, rid, gaps, end, source = tk.fresh(docs, "did", "rid", "gaps", "end", "source")
    gone = keep(gone.toDF(did, rid, gaps, end, source), "gone")
    key = [k.alias(n) for k, n in zip(_ids(), ("did", "rid"))]
    # the list of changed texts grows with the corpus, so its join is the same at every size
    both = docs.join(gone.hint("shuffle_hash"), (key[0] == gone[did]) & (key[1] == gone[rid]) & docs["text"].isNotNull(), "left")
    lines = F.split(docs["text"], "\n", -1)
    left = F.concat(F.flatten(F.transform(gone[gaps], lambda g: F.slice(lines, g["at"] + 1, g["n"]))), F.slice(lines, gone[end] + 1, F.size(lines)))
    removed = F.coalesce(gone[end] - F.aggregate(gone[gaps], F.lit(0), lambda s, g: s + g["n"]), F.lit(0))
    text = F.when(gone[gaps].isNull(), docs["text"]).otherwise(F.array_join(left, "\n"))
    size = F.when(gone[gaps].isNull(), docs["n_chars"]).otherwise(F.length(text)) if "n_chars" in docs.columns else None
    cols = [text.alias(c) if c == "text" else size.cast(dict(docs.dtypes)[c]).alias(c) if c == "n_chars" else docs[f"`{c}`"] for c in docs.columns]
    return both.select(*cols, removed.alias("removed_lines"), F.coalesce(gone[source], F.array().cast("array<bigint>")).alias("copied_from"))
