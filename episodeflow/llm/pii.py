"""Personal data found by patterns, confirmed by checksums and scored by the words around it; DataFrame functions only.

Patterns propose spans, leftmost and non-overlapping within a kind. `card` needs 13 to 19 digits that pass Luhn, `iban`
a valid mod-97 remainder; `ip` parts of at most 255, `phone` 9 to 15 digits; `ssn` has no checksum, so it stands only
where a context word lies near. Each kind has a base score; a context word within `WINDOW` characters before or after
raises it. Spans are code points, end exclusive.

Words and numbers may follow an account number after a space, so its pattern proposes only where one may begin, each
apart from the others. Of the ends at a word border after 15 to 34 letters and digits, the one that gives the country's
length is taken if it is valid, else the last valid one. A number that begins within another is left out.

The patterns are written with possessive repeats and start only where a run begins or the last match ended. That finds
the spans of the plain patterns in linear time and without recursion, however long a run of digits or letters is.

Null texts are empty; empty texts have no spans; ties can't arise within a kind (spans don't overlap), while kinds may
overlap each other; repeated rows are judged one by one; other columns aren't read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import texts

#: Kind, pattern, base score, score with a context word, context words.
KINDS = [
    ("email", r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++", 0.9, 1.0, r"mail|contact|courriel|correo|write"),
    ("ip", r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++", 0.6, 0.95, r"\bip\b|address|server|host|adresse"),
    ("card", r"[0-9](?:[\x20-]?[0-9])++", 0.8, 1.0, r"card|visa|carte|karte|tarjeta|credit|payment"),
    ("phone", r"\+[0-9][\x20().0-9-]+[0-9]", 0.7, 0.95, r"phone|call|tel|mobile|fax"),
    ("iban", r"(?<![A-Za-z0-9])[A-Z]{2}(?=[0-9]{2}(?:[\x20]?[A-Z0-9]){11})", 0.9, 1.0, r"iban|bank|account|konto|compte|cuenta"),
    ("ssn", r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])", 0.0, 0.85, r"ssn|social|security|tax"),
]
BASE = ["email", "ip", "card", "phone"]
WINDOW, CHUNK = 40, 128
#: The most characters of an account number with its spaces; the countries' lengths.
LONGEST = 67
LENGTHS = dict(zip(
    "AD AE AL AT AZ BA BE BG BH BR BY CH CR CY CZ DE DK DO EE EG ES FI FO FR GB GE GI GL GR GT HR HU IE IL IQ IS IT JO KW KZ LB LC LI LT LU LV LY MC MD ME MK MR MT MU NL NO PK PL PS PT QA RO RS SA SC SE SI SK SM ST SV TL TN TR UA VA VG XK".split(),
    (24, 23, 28, 20, 28, 20, 16, 22, 22, 29, 28, 21, 22, 28, 24, 22, 18, 28, 20, 29, 24, 18, 18, 27, 22, 22, 23, 18, 27, 28, 21, 28, 22, 23, 23, 26, 27, 30, 30, 20, 28, 32, 21, 20, 20, 21, 25, 27, 24, 22, 19, 27, 31, 30, 18, 15, 24, 28, 29, 25, 29, 24, 22, 24, 31, 24, 19, 24, 27, 25, 28, 23, 24, 26, 29, 22, 24, 20),
    strict=True,
))
BYTE = r"^0*(?:[0-9]{1,2}|1[0-9]{2}|2[0-4][0-9]|25[0-5])$"


def _luhn(digits: Column) -> Column:
    """Whether the digits pass: every second one from the right doubled, nines cast out, the sum a multiple of ten."""
    each = F.transform(F.split(F.reverse(digits), ""), lambda d, i: F.when(i % 2 == 0, d.cast("int")).otherwise(F.element_at(F.array(*[F.lit(x) for x in (0, 2, 4, 6, 8, 1, 3, 5, 7, 9)]), d.cast("int") + 1)))
    return F.aggregate(each, F.lit(0), lambda a, x: a + F.coalesce(x, F.lit(0))) % 10 == 0


def _mod97(code: Column) -> Column:
    """Whether an account number, spaces out and head moved behind, leaves 1 with A = 10 ... Z = 35."""
    turned = F.concat(F.substring(code, 5, 40), F.substring(code, 1, 4))
    each = F.filter(F.split(turned, ""), lambda c: c != "")
    value = F.transform(each, lambda c: F.when(c.rlike("[0-9]"), c.cast("int")).otherwise(F.ascii(c) - 55))
    return F.aggregate(value, F.lit(0), lambda a, v: F.when(v > 9, (a * 100 + v) % 97).otherwise((a * 10 + v) % 97)) == 1


def _valid(kind: str, value: Column, context: Column) -> Column:
    if kind == "ip":
        return F.forall(F.split(value, r"\."), lambda p: p.rlike(BYTE))
    digits = F.regexp_replace(value, "[^0-9]", "")
    if kind == "card":
        return F.when(F.length(digits).between(13, 19), _luhn(digits)).otherwise(F.lit(False))
    if kind == "phone":
        return F.length(digits).between(9, 15)
    return context if kind == "ssn" else F.lit(True)


def _placed(gaps: Column, found: Column) -> Column:
    """(start, end, value, number) of each match. The sums run chunk by chunk, so that long arrays don't cost their square."""
    n = F.size(found)
    span = "struct<at:int,out:array<struct<s:int,e:int,v:string,i:int>>>"
    empty = F.lit(None).cast("array<struct<s:int,e:int,v:string,i:int>>")

    def chunk(base: Column, k: Column) -> Column:
        ids = F.sequence(k * CHUNK, F.least((k + 1) * CHUNK, n) - 1)
        start = F.struct(base.alias("at"), F.coalesce(empty, F.array().cast("array<struct<s:int,e:int,v:string,i:int>>")).alias("out")).cast(span)

        def step(a: Column, i: Column) -> Column:
            left, value = F.get(gaps, i), F.get(found, i)
            s = a["at"] + F.length(left)
            e = s + F.length(value)
            item = F.struct(s.alias("s"), e.alias("e"), value.alias("v"), i.alias("i"))
            return F.struct(e.alias("at"), F.concat(a["out"], F.array(item)).alias("out")).cast(span)

        return F.aggregate(ids, start, step)

    many = "struct<at:int,out:array<array<struct<s:int,e:int,v:string,i:int>>>>"

    def outer(a: Column, k: Column) -> Column:
        got = F.transform(F.array(a["at"]), lambda base: chunk(base, k))  # bound once
        return F.element_at(F.transform(got, lambda c: F.struct(c["at"].alias("at"), F.concat(a["out"], F.array(c["out"])).alias("out")).cast(many)), 1)

    ran = F.aggregate(F.sequence(F.lit(0), F.floor((n - 1) / CHUNK).cast("int")), F.struct(F.lit(0).alias("at"), F.array().cast("array<array<struct<s:int,e:int,v:string,i:int>>>").alias("out")).cast(many), outer)
    return F.when(n > 0, F.flatten(ran["out"])).otherwise(F.array().cast("array<struct<s:int,e:int,v:string,i:int>>"))


def _before(gaps: Column, found: Column, i: Column, most: int) -> Column:
    """The `most` characters before match i, put together from gaps and matches (of two characters at least)."""
    n, last = F.least(i, F.lit(most // 2)), lambda x: F.right(x, F.lit(most))
    each = F.zip_with(F.slice(gaps, i - n + 1, n), F.slice(found, i - n + 1, n), lambda g, f: F.concat(last(g), last(f)))
    return last(F.concat(F.array_join(each, ""), last(F.get(gaps, i))))


def _after(gaps: Column, found: Column, i: Column, most: int) -> Column:
    """The `most` characters after match i."""
    n, first = F.lit(most // 2), lambda x: F.left(x, F.lit(most))
    n = F.least(n, F.size(found) - i - 1)
    each = F.zip_with(F.slice(found, i + 2, n), F.slice(gaps, i + 3, n), lambda f, g: F.concat(first(f), first(g)))
    return first(F.concat(first(F.get(gaps, i + 1)), F.array_join(each, "")))


def _accounts(heads: Column, gaps: Column, found: Column) -> Column:
    """The valid account numbers that begin at the placed heads."""
    kind = "array<struct<s:int,e:int,v:string,i:int>>"

    def ends(text: Column) -> Column:
        run = F.regexp_extract(text, "^[A-Z]{2}[0-9]{2}(?:[ ]?[A-Z0-9]){11,30}", 0)
        border = F.filter(F.sequence(F.lit(15), F.length(run)), lambda p: (F.substring(text, p, F.lit(1)) != " ") & ~F.substring(text, p + 1, F.lit(1)).rlike("[A-Za-z0-9]"))
        codes = F.transform(border, lambda p: F.struct(p.alias("p"), F.regexp_replace(F.substring(text, F.lit(1), p), " ", "").alias("c")))
        valid = F.filter(codes, lambda x: F.when(F.length(x["c"]).between(15, 34), _mod97(x["c"])).otherwise(F.lit(False)))
        length = F.create_map(*[F.lit(x) for pair in LENGTHS.items() for x in pair])
        return F.array_max(F.transform(valid, lambda x: F.struct(F.coalesce(F.length(x["c"]) == F.try_element_at(length, F.left(x["c"], F.lit(2))), F.lit(False)).alias("own"), x["p"].alias("p"))))["p"]

    def whole(x: Column) -> Column:
        text = F.concat(x["v"], _after(gaps, found, x["i"], LONGEST))
        return F.element_at(F.transform(F.array(text), lambda t: F.element_at(F.transform(F.array(ends(t)), lambda p: F.struct(x["s"].alias("s"), (x["s"] + p).alias("e"), F.left(t, p).alias("v"), x["i"].alias("i"))), 1)), 1)

    every = F.filter(F.transform(heads, whole), lambda x: x["e"].isNotNull())
    meet = F.exists(F.zip_with(every, F.slice(every, F.lit(2), F.size(every)), lambda x, y: F.coalesce(y["s"] < x["e"], F.lit(False))), lambda b: b)
    apart = F.aggregate(every, F.array().cast(kind), lambda a, x: F.when(F.coalesce(F.get(a, F.size(a) - 1)["e"] > x["s"], F.lit(False)), a).otherwise(F.concat(a, F.array(x)).cast(kind)))
    return F.when(F.size(heads) == 0, F.array().cast(kind)).when(meet, apart).otherwise(every)


def _confirmed(kind: str, _pattern: str, low: float, high: float, words: str) -> Column:
    """The placed matches of a kind that are valid, each with its score."""

    def near(x: Column) -> Column:
        gaps, found = F.col(f"_g_{kind}"), F.col(f"_m_{kind}")
        after = _after(gaps, found, x["i"], WINDOW)
        if kind == "iban":  # only its head is a match
            after = F.substring(_after(gaps, found, x["i"], LONGEST + WINDOW), F.length(x["v"]) - 1, F.lit(WINDOW))
        return F.lower(F.concat_ws(" | ", _before(gaps, found, x["i"], WINDOW), after)).rlike(words)

    right = F.filter(F.col(f"_p_{kind}"), lambda x: _valid(kind, x["v"], near(x)))
    return F.transform(right, lambda x: F.struct(F.lit(kind).alias("kind"), x["s"].alias("start"), x["e"].alias("end"), F.when(near(x), F.lit(high)).otherwise(F.lit(low)).alias("score")))


def find(docs: DataFrame, *more: str) -> DataFrame:
    """doc_id, text, `more` and the spans in one column, `_spans`: for each of KINDS those by start, (kind, start, end, score).

    `more` may hold columns of any name but those that begin with an underscore.
    """
    df = texts(docs, *[F.col(f"`{c}`") for c in more])
    need = {"email": "@", "phone": "+"}  # kinds that can't occur without this
    for kind, pattern, *_ in KINDS:
        some = F.col("text").contains(need[kind]) if kind in need else F.col("text").rlike("[0-9]")
        none = F.array().cast("array<string>")
        df = df.withColumn(f"_m_{kind}", F.when(some, F.expr(f"regexp_extract_all(text, r'{pattern}', 0)")).otherwise(none))
    for kind, pattern, *_ in KINDS:
        df = df.withColumn(f"_g_{kind}", F.when(F.size(f"_m_{kind}") > 0, F.split("text", pattern, -1)).otherwise(F.array().cast("array<string>")))
    df = df.withColumns({f"_p_{kind}": _placed(F.col(f"_g_{kind}"), F.col(f"_m_{kind}")) for kind, *_ in KINDS})
    df = df.withColumn("_p_iban", _accounts(F.col("_p_iban"), F.col("_g_iban"), F.col("_m_iban")))
    df = df.withColumns({f"_s_{k[0]}": _confirmed(*k) for k in KINDS})
    return df.select("doc_id", "text", *[F.col(f"`{c}`") for c in more], F.struct(*[F.col(f"_s_{k}").alias(k) for k, *_ in KINDS]).alias("_spans"))


def spans(kind: str) -> Column:
    return F.col("_spans")[kind]


def _listed(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",")


def report(docs: DataFrame) -> DataFrame:
    """Counts of the base kinds, a digest of their spans, all spans, and the highest score (null: no span)."""
    df = find(docs)
    base, every = F.concat(*map(spans, BASE)), F.concat(*[spans(k) for k, *_ in KINDS])
    return df.select(
        "doc_id",
        *[F.size(spans(k)).cast("long").alias(f"n_{k}") for k in BASE],
        F.sha2(_listed(base), 256).alias("base_sha256"),
        _listed(every).alias("spans"),
        F.array_max(F.transform(every, lambda x: x["score"])).alias("max_score"),
    )


def redact(docs: DataFrame, keep: list[str]) -> DataFrame:
    """Documents with every span replaced by its kind in angle brackets; overlapping spans: the one that starts first.

    `keep` names the columns that go along, in their order and under their names, whatever these are. Texts without
    spans stay as they are, nulls among them.
    """
    packed = docs.select("doc_id", "text", F.struct(*[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(keep)]).alias("_row"))
    found = find(packed, "_row")
    every = F.array_sort(F.concat(*[F.transform(spans(k), lambda x: F.struct(x["start"].alias("s"), (-x["end"]).alias("e"), x["kind"].alias("k"))) for k, *_ in KINDS]))
    kind = "struct<at:int,out:array<string>>"
    df = found.withColumn("_all", every)
    walked = F.aggregate(
        F.col("_all"),
        F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("out")).cast(kind),
        lambda a, x: F.when(x["s"] < a["at"], a).otherwise(F.struct((-x["e"]).alias("at"), F.concat(a["out"], F.array(F.substring(F.col("text"), a["at"] + 1, x["s"] - a["at"]), F.concat(F.lit("<"), x["k"], F.lit(">")))).alias("out")).cast(kind)),
    )
    df = df.withColumn("_w", F.when(F.size("_all") > 0, walked))
    as_is = F.col("_row")[f"c{keep.index('text')}"]
    text = F.when(F.size("_all") > 0, F.concat(F.array_join(F.col("_w")["out"], ""), F.expr("substring(text, _w.at + 1)"))).otherwise(as_is)
    return df.select(*[text.alias(c) if c == "text" else F.col("_row")[f"c{i}"].alias(c) for i, c in enumerate(keep)])
