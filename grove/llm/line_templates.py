"""Line de-duplication by a fixed-depth template tree.

A line walks down a tree of fixed depth: its number of words, then its first
``depth`` words, words with a digit standing as the wildcard. Under a branch that
``min_docs`` different texts reach, a word is constant at its position if that many
texts have it there, and variable (the wildcard) otherwise; what results is the
line's template. A template met in ``min_docs`` different texts recurs: its lines
are dropped everywhere but in the text that has it first (least id).

Prose that only shares a beginning is left alone: wildcards from rarity are allowed
in at most a quarter of a line's words, and only in lines of at least ``wild_words``.
So are rows of numbers: at least half of a template's words must be real ones.

Only DataFrame functions run. Texts that are equal count as one document, so copies
of a page keep their lines; that is another operator's work. The first pass shuffles
a hash and a digest per line, no text; only lines under recurring branches carry
their words on. Counts are combined before a shuffle and hot joins can be split, so
no task holds all lines of a hot template.

Lines of fewer than ``depth`` words have no tree to walk. With ``short`` they recur by
their exact words, digits included, under the same ``min_docs``; without it they stay,
as the SQL of ``op9_line_templates`` has it.

Defined results: null and empty texts have no lines and stay; lines without a word are
never dropped; order and separators of kept lines are unchanged.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from grove.session import cut, drop_cut

WILD = "<*>"
SPACE = "[\\x20\\x09-\\x0D]+"
#: A word with a digit, entered at its first sign only.
_DIGIT_WORD = "(?<![^ ])[^ 0-9]*+[0-9][^ ]*+"
#: Up to so many numbers of a side are broadcast; beyond it the join is a shuffle.
BROADCAST_NUMBERS = 2_000_000


def _spaced(line: Column) -> Column:
    """The line's words with one space between; most lines are so already and only looked at."""
    odd = F.lit(False)
    for c in ("  ", "\t", "\x0b", "\x0c", "\r"):
        odd = odd | line.contains(c)
    return F.when(odd | line.startswith(" ") | line.endswith(" "), F.trim(F.regexp_replace(line, SPACE, " "))).otherwise(line)


def _masked(words: Column) -> Column:
    """Words with a digit become the wildcard."""
    return F.when(words.rlike("[0-9]"), F.regexp_replace(words, _DIGIT_WORD, WILD)).otherwise(words)


def _lines(docs: DataFrame) -> DataFrame:
    """(id, digest, pos, words, n): every line that has a word."""
    split = docs.where("text is not null").select(
        F.coalesce(F.col("doc_id").cast("long"), F.lit(2**63 - 1)).alias("id"), F.md5("text").alias("digest"), F.posexplode(F.split("text", "\n")).alias("pos", "line")
    )
    words = split.select("id", "digest", "pos", _spaced(F.col("line")).alias("words"))
    n = F.octet_length("words") - F.octet_length(F.replace("words", F.lit(" "), F.lit(""))) + 1
    return words.select("*", n.alias("n")).where(F.col("words") != "")


def _deep(lines: DataFrame, depth: int) -> DataFrame:
    """(id, digest, pos, words, branch): the lines of at least ``depth`` words."""
    return lines.where(F.col("n") >= depth).select("id", "digest", "pos", "words", F.xxhash64("n", _masked(F.substring_index("words", " ", depth))).alias("branch"))


def _short(lines: DataFrame, depth: int, min_docs: int) -> DataFrame:
    """(branch, template, digest, id, pos): shorter lines whose exact words ``min_docs`` texts have."""
    few = lines.where(F.col("n") < depth).select("id", "digest", "pos", F.xxhash64("n", "words").alias("branch"), F.md5("words").alias("template"))
    held = few.select("branch", "template", "digest").distinct().groupBy("branch", "template").agg(F.count("*").alias("texts")).where(F.col("texts") >= min_docs)
    common = cut(held.select("branch", "template"), "short")
    return few.join(_small(common, F.lit(2)), ["branch", "template"]).select("branch", "template", "digest", "id", "pos")


def _small(df: DataFrame, numbers: Column) -> DataFrame:
    """With a hint to broadcast, if its rows hold few numbers in all, counted first."""
    held = df.agg(F.sum(numbers)).first()[0] or 0
    return F.broadcast(df) if held <= BROADCAST_NUMBERS else df


def recurring_lines(docs: DataFrame, depth: int = 3, min_docs: int = 3, wild_words: int = 8, short: bool = False) -> DataFrame:
    """(digest, drops): for each text with lines to drop, their positions (from 0).

    ``docs`` has doc_id and text; digest is the md5 of the text."""
    every = _lines(docs)
    lines = _deep(every, depth)
    reached = cut(lines.select("branch", "digest").distinct().groupBy("branch").agg(F.count("*").alias("texts")).where(F.col("texts") >= min_docs).select("branch"), "reached")
    shaped = lines.join(_small(reached, F.lit(1)), "branch").select("id", "digest", "pos", "branch", _masked(F.col("words")).alias("shape"))
    under = cut(shaped.withColumn("key", F.xxhash64("shape")), "branches")
    shapes = (
        under.select("branch", "key", "digest").distinct().groupBy("branch", "key").agg(F.count("*").alias("texts"))
        .join(under.select("branch", "key", "shape").dropDuplicates(["branch", "key"]), ["branch", "key"])
    )
    # a row per word carries its shape's key, not its text: else a line would cost the square of its length
    spread = cut(shapes.select("branch", "key", "texts", F.posexplode(F.split("shape", " ")).alias("at", "word")), "words")
    support = spread.groupBy("branch", "at", "word").agg(F.sum("texts").alias("support")).where(F.col("support") >= min_docs).select("branch", "at", "word", F.lit(True).alias("constant"))
    template = (
        spread.drop("texts").join(support, ["branch", "at", "word"], "left")
        .groupBy("branch", "key")
        .agg(
            F.count("*").alias("n"),
            F.count("constant").alias("held"),
            F.count(F.when(F.col("constant") & (F.col("word") != WILD), 1)).alias("real"),
            F.array_join(
                F.transform(F.array_sort(F.collect_list(F.struct("at", F.when(F.col("constant"), F.col("word")).otherwise(WILD).alias("word")))), lambda x: x["word"]), " "
            ).alias("template"),
        )
        .where((2 * F.col("real") >= F.col("n")) & ((F.col("held") == F.col("n")) | ((F.col("n") >= wild_words) & (4 * F.col("held") >= 3 * F.col("n")))))
        .select("branch", "key", F.md5("template").alias("template"))
    )
    found = under.drop("shape").join(template, ["branch", "key"]).select("branch", "template", "digest", "id", "pos")
    matched = cut(found.unionByName(_short(every, depth, min_docs)) if short else found, "matched")
    recurs = (
        matched.groupBy("branch", "template", "digest")
        .agg(F.min("id").alias("id"))
        .groupBy("branch", "template")
        .agg(F.count("*").alias("texts"), F.min(F.struct("id", "digest")).alias("first"))
        .where(F.col("texts") >= min_docs)
        .select("branch", "template", F.col("first.digest").alias("first"))
    )
    out = cut(matched.join(recurs, ["branch", "template"]).where(F.col("digest") != F.col("first")).groupBy("digest").agg(F.collect_set("pos").alias("drops")), "drops")
    for done in (reached, under, spread, matched):
        drop_cut(done)
    return out


def drop_recurring(docs: DataFrame, depth: int = 3, min_docs: int = 3, wild_words: int = 8, short: bool = False) -> DataFrame:
    """``docs`` with all its columns, recurring lines taken out of ``text``; beside them
    ``_n_lines`` and ``_n_dropped``. No row is dropped, a text may become empty."""
    found = recurring_lines(docs, depth, min_docs, wild_words, short)
    drops = _small(found.withColumnsRenamed({"digest": "_digest", "drops": "_drops"}), 8 + F.size("_drops"))
    joined = docs.withColumn("_digest", F.md5("text")).join(drops, "_digest", "left")
    lines = F.split("text", "\n")
    flags = F.transform(F.sequence(F.lit(0), F.size(lines) - 1), lambda i: F.array_contains("_drops", i))
    kept = F.array_join(F.transform(F.filter(F.arrays_zip(lines.alias("line"), flags.alias("gone")), lambda x: ~x["gone"]), lambda x: x["line"]), "\n")
    return joined.select(
        *[docs[c] if c != "text" else F.when(F.col("_drops").isNull(), F.col("text")).otherwise(kept).alias("text") for c in docs.columns],
        F.when(F.length("text") > 0, F.size(lines)).otherwise(0).cast("long").alias("_n_lines"),
        F.when(F.col("_drops").isNull(), 0).otherwise(F.size("_drops")).cast("long").alias("_n_dropped"),
    )
