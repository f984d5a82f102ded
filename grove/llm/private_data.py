"""Personal data by weak supervision.

Candidate spans come from patterns and a gazetteer of given names. Labelers vote on
each (+1 personal, -1 not, 0 no opinion): the pattern's own check, words of context
before it, a gazetteer of prefixes and names, the variety of its characters, and the
nearness of another candidate. Expectation-maximisation over the counts of vote
patterns estimates each labeler's reliability and each kind's share without any
true label; its posteriors train the final span classifier, a logistic model over
kind, votes and length. Spans of the four base kinds that pass their check are always
returned; the classifier decides on all other candidates.

Only DataFrame functions touch rows: a document's candidates stay in its row as one
array, so nothing is shuffled but the counts of vote patterns, at most
kinds * 3^labelers * lengths of them (a bound that doesn't grow with the data). The
driver fits both models on those counts, and the classifier returns as an expression.

Patterns are anchored at the first character of a run and possessive where that
changes no match, so very long runs are read once. Offsets are in code points.
Defined results: null text is empty; no candidates give empty spans.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from grove.session import cut

KINDS = ("email", "ip", "card", "phone", "secret", "key", "token", "ssn", "person")
BASE = 4
LABELERS = ("check", "context", "gazetteer", "variety", "company")
#: Given names of the gazetteer (fixed values).
NAMES = ("James", "John", "Robert", "Michael", "William", "David", "Mary", "Patricia", "Jennifer", "Linda", "Elizabeth", "Barbara", "Susan", "Jessica", "Sarah", "Karen", "Hans", "Peter", "Klaus", "Anna", "Pierre", "Jean", "Marie", "Sophie", "José", "Juan", "Carlos", "María", "Carmen", "Luis")
_L = "A-Za-z0-9._%+-"
PATTERNS = {
    "email": rf"(?:\G|(?<![{_L}]))[{_L}]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++(?:\.[0-9]++)(?:\.[0-9]++)(?:\.[0-9]++)",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
    "secret": r"(?i)\b(?:password|passwd|pwd|secret|api[_-]?key|access[_-]?token)[\x20]?[=:][\x20]?[^\x20\x09-\x0D]{6,200}",
    "key": r"\b(?:AKIA|ASIA)[0-9A-Z]{16}\b",
    "token": r"\b(?:[0-9a-f]{32}|[0-9a-f]{40}|[0-9a-f]{64})\b",
    "ssn": r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])",
    "person": rf"\b(?:{'|'.join(NAMES)})\x20\p{{Lu}}\p{{Ll}}{{1,30}}\b",
}
#: What a text must contain for the pattern to be worth trying.
_GATE = {"email": "@", "phone": "+", "secret": "(?i)pass|pwd|secret|key|token", "key": "A[KS]IA"}
CONTEXT = {
    "email": "mail|contact|write|@",
    "ip": r"\bip\b|address|host|server|login",
    "card": "card|visa|credit|pay|iban|account",
    "phone": "phone|call|tel|mobile|fax|contact|mail",
    "secret": "login|user|config|env|cred",
    "key": "key|aws|access|secret",
    "token": "key|token|secret|hash|auth",
    "ssn": "ssn|social|security",
    "person": "name|mr|mrs|ms|dr|contact|author|dear",
}
_AGAINST = r"version|isbn|issn|invoice|order|page|fig|line|doi|commit|sha"
CTX = 48
CHUNK = 64


def _located(text: Column, kind: str) -> Column:
    """array<struct<s, e, v, l>>: code-point start and end, match, and what is before it."""
    rx = PATTERNS[kind]
    pieces, hits = F.split(text, rx, -1), F.regexp_extract_all(text, F.lit(rx), F.lit(0))
    spans = "array<struct<s:int,e:int,v:string,l:string>>"

    def place(a: Column, x: Column) -> Column:
        start = a["at"] + F.length(x["p"])
        one = F.struct(start.alias("s"), (start + F.length(x["h"])).alias("e"), x["h"].alias("v"), F.lower(F.right(x["p"], F.lit(CTX))).alias("l"))
        return F.struct((start + F.length(x["h"])).alias("at"), F.concat(a["out"], F.array(one)).alias("out"))

    def chunk(a: Column, some: Column) -> Column:
        got = F.aggregate(some, F.struct(a["at"].alias("at"), F.expr(f"cast(array() as {spans})").alias("out")), place)
        return F.transform(F.array(got), lambda g: F.struct(g["at"].alias("at"), F.concat(a["out"], F.array(g["out"])).alias("out")))[0]

    # spans are appended in chunks, and chunks to each other, so that a text of n hits copies n * CHUNK + (n / CHUNK)^2 of them
    def placed(every: Column) -> Column:
        chunks = F.transform(F.sequence(F.lit(1), F.size(every), F.lit(CHUNK)), lambda i: F.slice(every, i, F.lit(CHUNK)))
        return F.flatten(F.aggregate(chunks, F.struct(F.lit(0).alias("at"), F.expr(f"cast(array() as array<{spans}>)").alias("out")), chunk)["out"])

    step = F.transform(F.array(F.arrays_zip(F.slice(pieces, 1, F.size(hits)).alias("p"), hits.alias("h"))), placed)[0]
    gate = _GATE.get(kind)
    none = F.expr("cast(array() as array<struct<s:int,e:int,v:string,l:string>>)")
    ok = F.lit(True) if gate is None else text.contains(gate) if len(gate) == 1 else text.rlike(gate)
    return F.when(ok & text.rlike(rx), step).otherwise(none)


def _digits(v: Column) -> Column:
    return F.regexp_replace(v, "[^0-9]", "")


def _passes(kind: str, v: Column) -> Column:
    n = F.length(_digits(v))
    if kind == "ip":
        part = lambda p: F.regexp_replace(p, "^0+(?=[0-9])", "")
        return F.forall(F.split(v, r"\."), lambda p: (F.length(part(p)) <= 3) & (F.lpad(part(p), 3, "0") <= "255"))
    if kind == "card":
        return n.between(14, 19) & F.call_function("luhn_check", _digits(v))
    if kind == "phone":
        return n.between(10, 15)
    if kind == "ssn":
        return ~v.rlike("^(?:000|666|9)|-00-|-0000$")
    return F.lit(True)


def _known(kind: str, v: Column) -> Column:
    """+1 or -1 from lists of prefixes, endings and names."""
    rx = {
        "email": r"\.(?:com|org|net|edu|gov|io|de|fr|es|uk|info)$",
        "card": r"^(?:4|5[1-5]|34|37|6011|65|2[2-7])",
        "phone": r"^\+(?:1|7|2[07]|3[0-469]|4[013-9]|5[1-8]|6[0-6]|8[1246]|9[0-58])",
        "key": "^AKIA",
        "person": f"^(?:{'|'.join(NAMES[:16])})",
        "ip": r"^(?!(?:0|127|255)\.)",
    }.get(kind)
    return F.lit(0) if rx is None else F.when(v.rlike(rx), 1).otherwise(-1)


def _voted(k: int, kind: str):
    """A located span as a candidate with the votes that need no other candidate."""

    def of(x: Column) -> Column:
        return F.struct(
            x["s"].alias("s"),
            F.lit(k).alias("k"),
            x["e"].alias("e"),
            F.coalesce(_passes(kind, x["v"]), F.lit(False)).alias("ok"),
            F.when(x["l"].rlike(CONTEXT[kind]), 1).when(x["l"].rlike(_AGAINST), -1).otherwise(0).alias("context"),
            _known(kind, x["v"]).alias("gazetteer"),
            F.when(F.size(F.array_distinct(F.split(x["v"], ""))) >= F.least(F.lit(6), F.length(x["v"]) / 3), 1).otherwise(-1).alias("variety"),
            F.least(F.lit(3), F.floor(F.log2(F.length(x["v"]) + 1) / 2)).cast("int").alias("len"),
        )

    return of


def _of_kind(k: int):
    return lambda x: x["k"] == k


def candidates(docs: DataFrame) -> DataFrame:
    """(doc_id, cands): array<struct<s, k, e, ok, votes, len>> of each row, by start then kind."""
    text = F.coalesce("text", F.lit(""))
    df = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("t"))
    for kind in KINDS:
        df = df.withColumn("c_" + kind, _located(F.col("t"), kind))
    parts = [F.transform("c_" + kind, _voted(k, kind)) for k, kind in enumerate(KINDS)]
    df = df.select("doc_id", F.array_sort(F.concat(*parts)).alias("c"))
    near = F.transform(
        "c",
        lambda x, i: F.struct(
            x["s"].alias("s"), x["k"].alias("k"), x["e"].alias("e"), x["ok"].alias("ok"), x["len"].alias("len"),
            F.array(
                F.when(x["ok"], 1).otherwise(-1),
                x["context"],
                x["gazetteer"],
                x["variety"],
                F.when(
                    F.coalesce(x["s"] - F.get("c", i - 1)["e"] < CTX, F.lit(False)) | F.coalesce(F.get("c", i + 1)["s"] - x["e"] < CTX, F.lit(False)), 1
                ).otherwise(0),
            ).alias("votes"),
        ),
    )
    return df.select("doc_id", near.alias("cands"))


def estimate(cells: list[tuple[int, tuple[int, ...], int, int]], rounds: int = 30) -> tuple[list[float], dict]:
    """Posterior of each cell (kind, votes, length, count), and the labelers' reliabilities
    P(vote | personal), P(vote | not), by expectation-maximisation. No opinion is no evidence."""
    kinds = sorted({c[0] for c in cells})
    share = {k: 0.7 for k in kinds}
    prior = {(1, 1): 0.8, (1, -1): 0.2, (0, 1): 0.3, (0, -1): 0.7}
    rely = {(j, y, v): prior[y, v] for j in range(len(LABELERS)) for y in (0, 1) for v in (-1, 1)}
    post = [0.5] * len(cells)
    for _ in range(rounds):
        for n, (k, votes, _len, _c) in enumerate(cells):
            a = math.log(share[k]) + sum(math.log(rely[j, 1, v]) for j, v in enumerate(votes) if v)
            b = math.log(1 - share[k]) + sum(math.log(rely[j, 0, v]) for j, v in enumerate(votes) if v)
            post[n] = 1 / (1 + math.exp(min(60, max(-60, b - a))))
        for k in kinds:
            own = [(p, c[3]) for p, c in zip(post, cells, strict=True) if c[0] == k]
            share[k] = min(0.99, max(0.01, (sum(p * c for p, c in own) + 7) / (sum(c for _, c in own) + 10)))
        for j in range(len(LABELERS)):
            for y in (0, 1):
                mass = {v: 20 * prior[y, v] for v in (-1, 1)}
                for p, c in zip(post, cells, strict=True):
                    if c[1][j]:
                        mass[c[1][j]] += c[3] * (p if y else 1 - p)
                for v in mass:
                    rely[j, y, v] = mass[v] / sum(mass.values())
    return post, {"share": share, "rely": rely}


def _inputs(k: int, votes: tuple[int, ...], size: int) -> list[int]:
    """Indices of the classifier's active inputs: kind, each vote that was cast, length."""
    return [k, *[len(KINDS) + 3 * j + v + 1 for j, v in enumerate(votes) if v], len(KINDS) + 3 * len(LABELERS) + size]


def fit_classifier(cells: list, post: list[float], steps: int = 300, rate: float = 0.5) -> list[float]:
    """Logistic weights over :func:`_inputs`, trained on the posteriors as soft labels."""
    w = [0.0] * (len(KINDS) + 3 * len(LABELERS) + 4)
    total = sum(c[3] for c in cells) or 1
    for _ in range(steps):
        grad = [1e-3 * x for x in w]
        for (k, votes, size, count), p in zip(cells, post, strict=True):
            at = _inputs(k, votes, size)
            y = 1 / (1 + math.exp(min(60, max(-60, -sum(w[i] for i in at)))))
            for i in at:
                grad[i] += count / total * (y - p)
        w = [x - rate * g for x, g in zip(w, grad, strict=True)]
    return w


def _joined(spans: Column, kind_of: Column) -> Column:
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.get(kind_of, x["k"]), x["s"].cast("string"), x["e"].cast("string"))), ",")


def find_personal(docs: DataFrame) -> DataFrame:
    """(doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans) for each row of docs(doc_id, text)."""
    c = cut(candidates(docs), "cands")
    counted = c.select(F.explode("cands").alias("x")).groupBy(F.col("x.k").alias("k"), F.col("x.votes").alias("votes"), F.col("x.len").alias("len")).agg(F.count("*").alias("n"))
    cells = sorted((r.k, tuple(r.votes), r.len, r.n) for r in counted.collect())  # at most kinds * 3^labelers * 4 rows
    post, _ = estimate(cells)
    w = fit_classifier(cells, post)
    weight = F.array(*[F.lit(float(x)) for x in w])

    def says(x: Column) -> Column:
        z = F.get(weight, x["k"]) + F.get(weight, F.lit(len(KINDS) + 3 * len(LABELERS)) + x["len"])
        for j in range(len(LABELERS)):
            z = z + F.get(weight, F.lit(len(KINDS) + 3 * j + 1) + F.get(x["votes"], F.lit(j)))
        return z >= 0

    base = F.filter("cands", lambda x: (x["k"] < BASE) & x["ok"])
    kept = F.filter("cands", lambda x: F.when(x["k"] < BASE, x["ok"]).otherwise(says(x)))
    names = F.array(*[F.lit(k) for k in KINDS])
    return c.select("doc_id", base.alias("base"), kept.alias("kept")).select(
        "doc_id",
        *[F.size(F.filter("base", _of_kind(k))).cast("long").alias("n_" + KINDS[k]) for k in range(BASE)],
        F.sha2(_joined(F.col("base"), names).cast("binary"), 256).alias("base_sha256"),
        _joined(F.col("kept"), names).alias("spans"),
    )
