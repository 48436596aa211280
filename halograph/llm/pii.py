"""Personal data by candidate gradient boosting, in SQL functions only.

The base patterns find spans that always stay. High-recall generators propose further, overlapping spans; boosted trees over format and
context features score them; those above their kind's calibrated threshold are added where they overlap no base span, best score first, each
unless it overlaps one that was added before. Spans are settled in clusters of overlapping ones, so a text with very many stays linear.
The trees are fitted on TRAIN_ROWS labelled candidates that are made by a seeded rule, so results don't depend on the table.

Positions are code points, end exclusive. Null text counts as empty. Repeated rows each get their own result, an empty table gives an
empty one, and other columns stay as they are. Nothing is shuffled. Spark has no function for positions of matches, so they are summed
up from the lengths of matches and of the gaps between them, in blocks so that texts with very many matches stay linear.
"""

from __future__ import annotations

import json
import random
from functools import cache, reduce

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .boosting import Boosted, fit
from .common import let, prefix_sums, prefixes, unused

KINDS = ("email", "ip", "card", "phone")

#: Base patterns in linear form: possessive, and begun only where a longer match can't begin earlier. They find the same spans.
_LOCAL = "[A-Za-z0-9._%+-]"
BASE = {
    "email": rf"(?:\G|(?<!{_LOCAL})){_LOCAL}++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"(?<![0-9])[0-9](?:[ -]?[0-9])++",
    "phone": r"\+[0-9][ ().0-9-]+[0-9]",
}
#: Texts without this can't have a match.
HINT = {"email": "@", "ip": "[0-9][.][0-9]", "card": "[0-9][ -]?[0-9]", "phone": r"\+[0-9]"}

_AT, _DOT = r"(?:@|\(at\)|\[at\]|\{at\})", r"(?:\.|\(dot\)|\[dot\]|\{dot\})"
LOOSE = {
    "email": (
        rf"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{{1,64}} ?{_AT} ?[A-Za-z0-9-]{{1,63}}(?: ?{_DOT} ?[A-Za-z0-9-]{{1,63}}){{1,5}}"
        r"|(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{1,64} at [A-Za-z0-9-]{1,63}(?: dot [A-Za-z0-9-]{1,63}){1,5}"
    ),
    "ip": r"(?<![0-9])[0-9]{1,3}(?: ?(?:\[\.\]|\(\.\)|\[dot\]|\(dot\)|\.) ?[0-9]{1,3}){3}(?![0-9])",
    "card": r"(?<![0-9])[0-9](?:[ .\-]{0,2}[0-9]){12,18}(?![0-9])",
    "phone": r"(?<![0-9+])\(?[0-9]{2,4}\)?[ .\-/]{1,2}[0-9]{2,4}(?:[ .\-][0-9]{2,4}){1,3}(?![0-9])",
}
LOOSE_HINT = {"email": r"@|[(\[{]at[)\]}]| dot ", "ip": r"[0-9] ?[\[(.]", "card": "[0-9][ .-]{0,2}[0-9]", "phone": r"[0-9]\)?[ .\-/]"}

# Words that stand before personal data, and before other numbers.
CUES = {
    "email": "mail|contact|write|reach|courriel|correo|kontakt",
    "ip": r"\bip\b|host|server|address|client|login|adresse",
    "card": "card|visa|credit|debit|payment|carte|karte|tarjeta",
    "phone": r"phone|\btel|call|mobile|\bcell|fax|dial|whatsapp|telefon",
}
OTHER = r"version|order|invoice|serial|isbn|ticket|total|price|\bid\b|token|hash|code|page|chapter|section|build|year|date"

BEFORE, AFTER = 24, 12
#: labelled candidates of each kind for the trees; every third is held out for calibration
TRAIN_ROWS = 900
SEED = 20


def located(text: Column, pattern: str, hint: str) -> Column:
    """Leftmost non-overlapping matches of a text as structs (s, at, before, after)."""

    def place(m: Column) -> Column:
        def with_gaps(gaps: Column) -> Column:
            steps = F.transform(m, lambda x, i: F.length(x) + F.length(F.get(gaps, i)))
            return let(
                prefix_sums(steps),
                lambda before: F.transform(
                    m,
                    lambda x, i: F.struct(
                        x.alias("s"),
                        (F.get(before, i) + F.length(F.get(gaps, i))).alias("at"),
                        F.right(F.get(gaps, i), F.lit(BEFORE)).alias("before"),
                        F.left(F.get(gaps, i + 1), F.lit(AFTER)).alias("after"),
                    ),
                ),
            )

        return F.when(F.size(m) > 0, let(F.split(text, pattern, -1), with_gaps))

    found = F.when(text.rlike(hint), let(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), place))
    return F.coalesce(found, F.array().cast("array<struct<s:string,at:int,before:string,after:string>>"))


def digits(s: Column) -> Column:
    return F.regexp_replace(s, "[^0-9]", "")


def luhn(number: Column) -> Column:
    """Whether a string of digits passes the checksum."""

    def total(d: Column) -> Column:
        return F.aggregate(
            F.transform(F.reverse(F.split(d, "")), lambda c, i: F.when(i % 2 == 0, c.cast("int")).otherwise((2 * c.cast("int")) % 10 + F.floor(c.cast("int") / 5).cast("int"))),
            F.lit(0),
            lambda a, b: a + b,
        )

    return let(number, lambda d: F.when(d == "", False).otherwise(total(d) % 10 == 0))


def octets(s: Column) -> Column:
    """Whether every run of digits is at most 255."""
    runs = F.regexp_extract_all(s, F.lit("[0-9]+"), F.lit(0))
    return F.forall(runs, lambda p: (F.length(F.regexp_replace(p, "^0+", "")) <= 3) & (F.right(p, F.lit(3)).cast("int") <= 255))


CHECK = {
    "email": lambda s: F.lit(True),
    "ip": octets,
    "card": lambda s: let(digits(s), lambda d: F.length(d).between(16, 19) & luhn(d)),
    "phone": lambda s: F.length(digits(s)).between(8, 15),
}

FEATURES = (
    "n_digits", "n_chars", "n_separators", "n_runs", "distinct_digits", "cue", "other_cue", "glued_left", "glued_right", "luhn", "octets",
    "leading_mark", "n_dots", "obfuscated", "last_label", "mixed_separators",
)


def features(c: Column, kind: str) -> list[Column]:
    """Format and context features of a candidate, in the order of FEATURES."""
    s, before, after = c["s"], c["before"], c["after"]
    flag = lambda x: x.cast("int")
    count = lambda p: F.size(F.regexp_extract_all(s, F.lit(p), F.lit(0)))
    return [
        F.length(digits(s)), F.length(s), count(r"[ ().\-/]"), count("[0-9]+"), F.size(F.array_distinct(F.split(digits(s), ""))),
        flag(before.rlike(f"(?i){CUES[kind]}")), flag(before.rlike(f"(?i){OTHER}")), flag(before.rlike(r"""[A-Za-z0-9_=/"#.\-]$""")),
        flag(after.rlike(r"""^(?:[A-Za-z0-9_%/"\-]|[.,][0-9])""")), flag(luhn(digits(s))), flag(octets(s)), flag(s.rlike(r"^[(+]")),
        count(r"\.|dot"), flag(s.rlike(r"(?i)\bat\b|\bdot\b|\[\.\]|\(\.\)")), F.length(F.regexp_extract(s, "([A-Za-z]*)$", 1)),
        F.size(F.array_distinct(F.regexp_extract_all(s, F.lit(r"[ .\-/]"), F.lit(0)))),
    ]


def _labelled(rng: random.Random, kind: str) -> tuple[str, str, str, int]:
    """One made candidate: text before, candidate, text after, label."""
    num = lambda n: "".join(rng.choice("0123456789") for _ in range(n))
    word = lambda a=3, b=9: "".join(rng.choice("abcdefghilmnoprstuv") for _ in range(rng.randint(a, b)))
    yes = rng.random() < 0.5
    cue = {
        "email": ["mail me: ", "contact ", "reach me under "], "ip": ["ip ", "server at ", "login from host "],
        "card": ["card number ", "credit card: ", "visa "], "phone": ["phone ", "tel. ", "call me at ", "fax: "],
    }[kind]
    odd = ["version ", "order ", "invoice no ", "serial ", "isbn ", "total ", "build ", "section ", f"{word()}=", f'"{word()}']
    # what stands before tells something, and not everything: a third of the true ones have no cue, and some others have one
    before = f"{word()} {rng.choice(cue)}" if rng.random() < (0.67 if yes else 0.15) else f"{word()} {word()} " if yes else f"{word()} {rng.choice([*odd, word() + ' '])}"
    after = rng.choice([" ", ". ", ", "]) + word() if yes or rng.random() < 0.4 else rng.choice(["-", "/", "_", '"', "", "%"]) + num(2)
    if kind == "email":
        if yes:
            at, dot = rng.choice([(" (at) ", " (dot) "), ("[at]", "[dot]"), (" at ", " dot "), ("{at}", "."), ("(at)", ".")])
            return before, f"{word()}.{word()}{at}{word()}{dot}{rng.choice(['com', 'org', 'net', 'de', 'fr'])}", after, 1
        return before, rng.choice([f"{word()} @ {word()}. {word()}", f"{word()} at {word()} dot {word(8, 12)}", f"{word()}@ {word()} .{num(2)}"]), after, 0
    if kind == "ip":
        sep = rng.choice(["[.]", "(.)", "[dot]", "(dot)"]) if yes else rng.choice([".", " . ", ". ", "[.]"])
        return before, sep.join(str(rng.randint(0, 255) if yes else rng.randint(0, 999)) for _ in range(4)), after, int(yes)
    if kind == "card":
        if yes:
            body = num(14 if rng.random() < 0.3 else 15)
            check = next(c for c in "0123456789" if _luhn(body + c))
            d = body + check
            sep = rng.choice([".", "  ", " - "[:2], "-", " "])
            return before, sep.join(d[i : i + 4] for i in range(0, len(d), 4)), after, 1
        d = num(rng.randint(13, 19))
        return before, rng.choice([d, ".".join(d[i : i + 3] for i in range(0, len(d), 3))]), after, 0
    if yes:
        sep = rng.choice(["-", " ", "."])
        return before, rng.choice([f"({num(3)}) {num(3)}-{num(4)}", sep.join([num(3), num(3), num(4)]), sep.join(["0" + num(2), num(3), num(4)])]), after, 1
    return before, rng.choice([f"{num(4)}-{num(2)}-{num(2)}", f"{num(2)}/{num(2)} {num(4)}", f"{num(4)} {num(4)} {num(4)}", f"{num(2)}.{num(3)}.{num(3)}"]), after, 0


def _luhn(number: str) -> bool:
    return sum(sum(divmod(2 * int(c), 10)) if i % 2 else int(c) for i, c in enumerate(reversed(number))) % 10 == 0


@cache
def _sample(kind: str) -> str:
    rng = random.Random(f"{SEED}-{kind}")
    return json.dumps([dict(zip(("before", "s", "after", "y"), _labelled(rng, kind), strict=True)) for _ in range(TRAIN_ROWS)])


_MODELS: dict[str, Boosted] = {}


def models(spark: SparkSession) -> dict[str, Boosted]:
    """The fitted trees of each kind. Their features come from the same SQL expressions that score the corpus."""
    for kind in KINDS:
        if kind not in _MODELS:
            rows = spark.range(1).select(F.inline(F.from_json(F.lit(_sample(kind)), "array<struct<before:string,s:string,after:string,y:int>>")))
            c = F.struct("s", "before", "after")
            got = np.array([list(r) for r in rows.select(*[f.cast("double") for f in features(c, kind)], F.col("y").cast("double")).collect()])
            _MODELS[kind] = fit(got[:, :-1], got[:, -1], np.arange(len(got)) % 3 == 2)
    return _MODELS


_SPAN = "array<struct<kind:int,at:int,end:int,score:double,added:boolean>>"


def settled(spans: Column) -> Column:
    """Of base and proposed spans, sorted by start, those that stay: all base ones, and greedily the best of the others. A cluster ends
    where a span begins that no earlier one reaches."""
    meets = lambda a, b: (a["at"] < b["end"]) & (b["at"] < a["end"])
    # sorted upwards, the best comes first
    order = lambda s: F.struct((-s["score"]).alias("a"), (s["at"] - s["end"]).alias("b"), s["at"].alias("c"), s["kind"].alias("d"), s["end"].alias("e"), s["score"].alias("f"))
    back = lambda o: F.struct(o["d"].alias("kind"), o["c"].alias("at"), o["e"].alias("end"), o["f"].alias("score"), F.lit(True).alias("added"))

    def greedy(c: Column) -> Column:
        ranked = F.transform(F.array_sort(F.transform(F.filter(c, lambda s: s["added"]), order)), back).cast(_SPAN)
        return F.aggregate(ranked, F.filter(c, lambda s: ~s["added"]), lambda done, s: F.when(F.exists(done, lambda x: meets(x, s)), done).otherwise(F.concat(done, F.array(s))))

    def of(s: Column) -> Column:
        reach = prefixes(F.transform(s, lambda x: x["end"]), lambda a, b: F.greatest(a, b))
        heads = let(reach, lambda r: F.filter(F.sequence(F.lit(0), F.size(s) - 1), lambda i: (i == 0) | (F.get(r, i) <= F.get(s, i)["at"])))
        clusters = let(heads, lambda h: F.transform(h, lambda i, k: F.slice(s, i + 1, F.coalesce(F.get(h, k + 1), F.size(s)) - i)))
        return F.flatten(F.transform(clusters, lambda c: F.when((F.size(c) > 1) & F.exists(c, lambda s: s["added"]), greedy(c)).otherwise(c)))

    return let(spans, of)


def find(docs: DataFrame, text: str = "text", name: str = "pii") -> DataFrame:
    """The input's columns and a struct called `name` (a column of that name is replaced): arrays base and spans of (kind, at, end, score,
    added), each sorted by kind, then start."""
    fitted = models(docs.sparkSession)
    whole = F.coalesce(docs[text], F.lit(""))

    def valid(kind: str):
        return lambda c: CHECK[kind](c["s"])

    def shaped(kind: str, found: Column) -> Column:
        k = F.lit(KINDS.index(kind))
        return F.transform(found, lambda c: F.struct(k.alias("kind"), c["at"].alias("at"), (c["at"] + F.length(c["s"])).alias("end"), F.lit(1.0).alias("score"), F.lit(False).alias("added"))).cast(_SPAN)

    base = F.concat(*[shaped(k, F.filter(located(whole, BASE[k], HINT[k]), valid(k))) for k in KINDS])

    def proposed(kind: str) -> Column:
        model = fitted[kind]
        scored = F.transform(
            located(whole, LOOSE[kind], LOOSE_HINT[kind]),
            lambda c: F.struct(
                F.lit(KINDS.index(kind)).alias("kind"), c["at"].alias("at"), (c["at"] + F.length(c["s"])).alias("end"),
                let(F.array(*[f.cast("double") for f in features(c, kind)]), lambda v: model.column([F.get(v, F.lit(i)) for i in range(len(FEATURES))])).alias("score"),
                F.lit(True).alias("added"),
            ),
        )
        return F.filter(scored, lambda s: s["score"] >= F.lit(model.threshold)).cast(_SPAN)

    by_start = lambda s: F.struct(s["at"].alias("at"), s["end"].alias("end"), s["added"].alias("added"), s["kind"].alias("kind"), s["score"].alias("score"))
    by_kind = lambda s: F.struct(*[s[c].alias(c) for c in ("kind", "at", "end", "score", "added")])

    def with_base(b: Column) -> Column:
        def merged(free: Column) -> Column:
            rows = F.transform(F.array_sort(F.transform(F.concat(b, free), by_start)), by_kind)
            return F.when(F.size(free) > 0, F.array_sort(settled(rows))).otherwise(b)

        return F.struct(b.alias("base"), let(F.concat(*[proposed(k) for k in KINDS]), merged).alias("spans"))

    empty = F.struct(F.array().cast(_SPAN).alias("base"), F.array().cast(_SPAN).alias("spans"))
    any_hint = reduce(lambda a, b: a | b, [whole.rlike("[0-9]"), whole.contains("@"), whole.rlike(LOOSE_HINT["email"])])
    return docs.withColumn(name, F.when(any_hint, let(base, with_base)).otherwise(empty))


def digest_text(spans: Column) -> Column:
    names = F.array(*map(F.lit, KINDS))
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["at"].cast("string"), s["end"].cast("string"))), ",")


def redact(docs: DataFrame, text: str = "text") -> DataFrame:
    """The input with every span replaced by its kind in brackets; spans that meet are replaced as one, named by the first."""
    name = unused(docs, "pii")
    found = find(docs, text, name)
    spans = F.col(name)["spans"]
    names = F.array(*[F.lit(f"[{k.upper()}]") for k in KINDS])
    kind = "array<struct<at:int,end:int,kind:int>>"
    ordered = F.array_sort(F.transform(spans, lambda s: F.struct(s["at"].alias("at"), s["end"].alias("end"), s["kind"].alias("kind"))))

    def apart(spans: Column) -> Column:
        """Spans that begin before an earlier one ends are joined to it."""

        def step(done: Column, s: Column) -> Column:
            last = F.element_at(done, -1)
            joined = F.struct(last["at"].alias("at"), F.greatest(last["end"], s["end"]).alias("end"), last["kind"].alias("kind"))
            return F.when((F.size(done) > 0) & (F.try_element_at(done, F.lit(-1))["end"] > s["at"]), F.concat(F.slice(done, F.lit(1), F.size(done) - 1), F.array(joined))).otherwise(F.concat(done, F.array(s)))

        return F.aggregate(spans, F.array().cast(kind), step)

    source = F.col(text)

    def replaced(s: Column) -> Column:
        parts = F.transform(s, lambda x, i: F.concat(F.substring(source, F.coalesce(F.get(s, i - 1)["end"], F.lit(0)) + 1, x["at"] - F.coalesce(F.get(s, i - 1)["end"], F.lit(0))), F.get(names, x["kind"])))
        return F.concat(F.array_join(parts, ""), F.substring(source, F.element_at(s, -1)["end"] + 1, F.lit(2147483647)))

    changed = F.when(F.size(spans) > 0, let(let(ordered, apart), replaced)).otherwise(source)
    return found.withColumn(text, changed).select(*docs.columns)


def op1_pii_boosting(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    p = find(docs)
    count = lambda k: F.size(F.filter(F.col("pii.base"), lambda s: s["kind"] == KINDS.index(k))).cast("long")
    counts = [count(k).alias(f"n_{k}") for k in KINDS]
    more = F.size("pii.spans") - F.size("pii.base")
    return p.select("doc_id", *counts, F.sha2(digest_text(F.col("pii.base")), 256).alias("base_sha256"), digest_text(F.col("pii.spans")).alias("spans"), more.cast("long").alias("n_added"))
