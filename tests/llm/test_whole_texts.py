"""No missed line or window."""

import collections
import itertools
import random
import re

import pandas as pd

from grove.llm import line_templates, spaced_seeds
from grove.session import table


def test_short_lines_recur(spark):
    long = "All rights reserved by the owner of this site"
    rows = [(i, f"Les.\nAnd   ornd.\nitem {i}\nown{i}\n7\n \n{long}") for i in range(4)] + [(9, "Les."), (10, None), (11, ""), (12, "own0\nown0")]
    d = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r.text for r in line_templates.drop_recurring(d, short=True).collect()}
    want = {i: f"item {i}\nown{i}\n " for i in (1, 2, 3)} | {0: rows[0][1], 9: "", 10: None, 11: "", 12: "own0\nown0"}
    assert got == want
    # against a count by hand on a given table
    e = pd.read_parquet("/root/testdata/sf0.01/documents.parquet")
    seen = collections.defaultdict(set)
    for t in e.text.dropna():
        for x in t.split("\n"):
            w = [y for y in re.split(r"[\x20\x09-\x0D]+", x) if y]
            if 0 < len(w) < 3:
                seen[" ".join(w)].add(t)
    common = {k for k, v in seen.items() if len(v) >= 3}
    out = line_templates.drop_recurring(table(spark, "/root/testdata/sf0.01", "documents"), short=True).toPandas()
    left = collections.defaultdict(set)
    for t in out.text.dropna():
        for x in set(t.split("\n")):
            k = " ".join(y for y in re.split(r"[\x20\x09-\x0D]+", x) if y)
            if k in common:
                left[k].add(t)
    assert len(common) >= 18 and all(len(v) <= 1 for v in left.values())


def test_no_window_is_missed(spark):
    for n in range(spaced_seeds.MIN_WORDS, 17):
        masks = spaced_seeds.MASKS if n >= 15 else spaced_seeds.SHORT_MASKS[10 if n >= 10 else 5]
        may = n - -(-80 * n // 100)
        for gone in itertools.combinations(range(n), may):
            assert any(all(at + k not in gone for k, c in enumerate(m) if c == "#") for m in masks for at in range(n - len(m) + 1)), (n, gone)
    r, rows, items, want = random.Random(4), [], [], set()
    for i, n in enumerate([5, 7, 9, 10, 12, 14, 15, 16, 16, 18, 40] * 6):
        item = [f"w{i}x{k}" for k in range(n)]
        items.append((i, " ".join(item)))
        size = min(16, n)
        begin, may = r.randrange(n - size + 1), size - -(-80 * size // 100)
        for j, m in enumerate((may, may + 1)):
            text = item[begin : begin + size]
            for k in r.sample(range(size), m):
                text[k] = "other"
            rows.append((2 * i + j, " ".join(["a", "b", *text, "c"])))
        want.add((2 * i, i))
    found = spaced_seeds.find_leaks(spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string"))
    assert {(x.doc_id, x.item_id) for x in found.collect()} == want
