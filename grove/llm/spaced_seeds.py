"""Benchmark decontamination by spaced-seed hashing.

A mask of ``#`` and ``-`` picks some word positions of a span and ignores the rest, so
a hash under the mask still meets when ignored words were replaced. Hashes of all
spans of the training texts are joined with those of the test items; each hit fixes
an alignment of a text with an item, and an alignment counts when some window of
``window`` words around it agrees in at least ``percent`` of its words.

Only DataFrame functions run. A text's words are hashed once; spans are hashed after
the explode, where the expression is compiled, and probed against the items' hashes.
Those are broadcast only after they have been counted and found small
(``max_broadcast`` hashes); larger benchmarks are joined by a shuffle.

No window that would count is missed: at 80 percent of 16 words, three replaced words
leave some mask whole wherever they stand, and so for shorter items with the fewer words
that these may have replaced (a test enumerates all places).

Defined results: words are runs of letters and digits, lower-cased; null and empty
texts have none; items shorter than a window are matched whole, if they have at least
``MIN_WORDS`` words, and shorter ones can't be told from chance and match nothing;
repeated rows are one text, repeated items match each.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from grove.session import cut

#: For items of 15 words and more: any 3 of 15 may be replaced.
MASKS = ("##-#-###", "###-----##-#", "#-##------###")
MIN_WORDS = 5
#: For shorter items, by their least number of words: any 2 of 10, any 1 of 5 may be replaced.
SHORT_MASKS = {10: ("###-##", "##---###", "#-##---##"), MIN_WORDS: ("###", "##-##")}
LONG = 15
NOT_WORD = "[^\\p{L}\\p{N}]+"


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(F.lower(text), NOT_WORD), "")


def _spans(df: DataFrame, keep: list[str], masks: list[tuple[int, str]]) -> DataFrame:
    """(keep..., at, seed) for every span of ``w`` under every numbered mask."""
    out = None
    for n, mask in masks:
        room = F.size("w") - len(mask)
        at = df.where(room >= 0).select(*keep, "w", F.explode(F.sequence(F.lit(0), room)).alias("at"))
        picked = [F.get("w", F.col("at") + k) for k, c in enumerate(mask) if c == "#"]
        one = at.select(*keep, "at", F.xxhash64(F.lit(n), *picked).alias("seed"))
        out = one if out is None else out.unionByName(one)
    return out


def _small(digests: DataFrame, most: int) -> DataFrame:
    """Written, and with a hint to broadcast if there are at most ``most``: else texts would be shuffled to meet a few."""
    named = cut(digests, "digests")
    return F.broadcast(named) if named.count() <= most else named


def find_leaks(docs: DataFrame, items: DataFrame, masks: tuple[str, ...] = MASKS, window: int = 16, percent: int = 80, max_broadcast: int = 2_000_000) -> DataFrame:
    """(doc_id, digest, item_id, doc_word, item_word, n_matched, n_words) for each text and item
    that share a window: the words from which, and the best window's agreement.

    ``docs`` has doc_id and text, ``items`` item_id and text; digest is the md5 of the text."""
    tests = cut(
        items.where("text is not null").select(F.col("item_id").cast("long").alias("item_id"), F.transform(words_of(F.col("text")), lambda x: F.xxhash64(x)).alias("w")).where(F.size("w") >= MIN_WORDS),
        "items",
    )
    kinds, number, plain, seeds = {LONG: masks, **SHORT_MASKS}, 0, [], None
    lead = F.when(F.size("w") >= LONG, LONG).when(F.size("w") >= 10, 10).otherwise(MIN_WORDS)
    for r in tests.select(lead.alias("kind")).distinct().orderBy("kind").collect():  # at most three numbers
        numbered = list(enumerate(kinds[r.kind], number))
        number += len(numbered)
        plain += numbered
        some = _spans(tests.where(lead == r.kind), ["item_id"], numbered)
        seeds = some if seeds is None else seeds.unionByName(some)
    if seeds is None:  # no items: the empty table's plan
        plain = list(enumerate(masks))
        seeds = _spans(tests, ["item_id"], plain)
    seeds = cut(seeds.select("item_id", F.col("at").alias("item_at"), "seed"), "seeds")
    small = seeds.count() <= max_broadcast

    texts = docs.where("text is not null").select(F.col("doc_id").cast("long").alias("doc_id"), F.md5("text").alias("digest"), F.transform(words_of(F.col("text")), lambda x: F.xxhash64(x)).alias("w"))
    spans = _spans(texts, ["doc_id", "digest"], plain)
    hits = cut(
        spans.join(F.broadcast(seeds) if small else seeds, "seed").select("doc_id", "digest", "item_id", (F.col("at") - F.col("item_at")).alias("shift")).distinct(),
        "hits",
    )
    hit_texts = texts.join(_small(hits.select("digest").distinct(), max_broadcast), "digest", "left_semi").groupBy("digest").agg(F.first("w").alias("w"))
    aligned = (
        hits.select("digest", "item_id", "shift").distinct()
        .join(tests.select("item_id", F.col("w").alias("v")), "item_id")
        .join(hit_texts, "digest")
        .withColumn("lo", F.greatest(F.lit(0), -F.col("shift")))
        .withColumn("hi", F.least(F.size("v"), F.size("w") - F.col("shift")))
        .withColumn("same", F.zip_with(F.slice("v", F.col("lo") + 1, F.col("hi") - F.col("lo")), F.slice("w", F.col("lo") + F.col("shift") + 1, F.col("hi") - F.col("lo")), lambda a, b: (a == b).cast("int")))
        .withColumn("n_words", F.least(F.lit(window), F.size("v")))
        .where(F.size("same") >= F.col("n_words"))
        .withColumn("at", F.explode(F.sequence(F.lit(0), F.size("same") - F.col("n_words"))))
        .withColumn("n_matched", F.aggregate(F.slice("same", F.col("at") + 1, F.col("n_words")), F.lit(0), lambda a, x: a + x))
        .where(100 * F.col("n_matched") >= percent * F.col("n_words"))
        .groupBy("digest", "item_id")
        .agg(F.max(F.struct("n_matched", (-(F.col("lo") + F.col("shift") + F.col("at"))).alias("d"), (-(F.col("lo") + F.col("at"))).alias("i"), "n_words")).alias("best"))
    )
    return (
        hits.select("doc_id", "digest", "item_id").distinct()
        .join(aligned, ["digest", "item_id"])
        .select("doc_id", "digest", "item_id", (-F.col("best.d")).cast("long").alias("doc_word"), (-F.col("best.i")).cast("long").alias("item_word"), F.col("best.n_matched").cast("long").alias("n_matched"), F.col("best.n_words").cast("long").alias("n_words"))
    )


def drop_leaks(docs: DataFrame, items: DataFrame, max_broadcast: int = 2_000_000, **options) -> DataFrame:
    """``docs`` with all its columns, without the rows whose text shares a window with an item."""
    found = find_leaks(docs, items, max_broadcast=max_broadcast, **options)
    bad = _small(found.select(F.col("digest").alias("_bad")).distinct(), max_broadcast)
    return docs.join(bad, F.md5(docs["text"]) == bad["_bad"], "left_anti")
