"""Personal data: regular expressions propose spans, validators confirm them, context words adjust the score.

DataFrame operations only.  A text is split at the matches of a pattern, and running totals of the lengths of the parts give the
positions; so offsets are code points.  Totals are taken in blocks of the square root of their number, as an array that grows by one
is copied each time, and texts are never cut by a position from their start, so texts with very many spans take no square of time.  Possessive quantifiers keep the matching linear and free of recursion on
very long texts; they change no match, as what follows never needs what they took.

Kinds: email, ip (parts at most 255), card (12 to 19 digits, Luhn), phone (9 to 15 digits), and of this method's own iban (mod 97)
and key (a long credential).  The context of a match is the 30 characters before it, no further back than the part before the last match.  Base kinds are always kept; the others need a score of at least 0.5 from pattern, validator and context.

Edge cases: a NULL text is empty and has no spans; repeated rows are scanned each by itself; spans of different kinds may overlap; an empty table gives an
empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from depstrata.llm.common import apart, held

# Patterns, and words before a match that speak for it.
PATTERNS = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[ -]?[0-9])++",
    "phone": r"\+[0-9][ ().0-9-]+[0-9]",
    "iban": r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]){11,30}+(?![A-Za-z0-9])",
    "key": r"(?<![A-Za-z0-9_-])(?=[A-Za-z_-]*[0-9])[A-Za-z0-9_-]{24,}+",
}
#: A cheap test that every text with a match passes.
HINTS = {
    "email": lambda t: F.contains(t, F.lit("@")),
    "ip": lambda t: t.rlike(r"[0-9]\.[0-9]++\.[0-9]++\.[0-9]"),
    "card": lambda t: t.rlike(r"[0-9](?:[ -]?[0-9]){11}"),
    "phone": lambda t: t.rlike(r"\+[0-9]"),
    "iban": lambda t: t.rlike(r"[A-Z]{2}[0-9]{2} ?[A-Z0-9]"),
    "key": lambda t: t.rlike(r"[A-Za-z0-9_-]{24}"),
}
CONTEXT = {
    "email": "mail|contact|write",
    "ip": "ip|host|server|address",
    "card": "card|visa|credit|pay",
    "phone": "phone|tel|call|fax|mobile",
    "iban": "iban|account|bank|konto",
    "key": "token|key|secret|passw|credential|auth",
}
#: Code points of a piece of a text that spans are cut from.
_CHUNK = 1024
BASE = ("email", "ip", "card", "phone")
KINDS = tuple(PATTERNS)


def _digits(m: Column) -> Column:
    return F.regexp_replace(m, "[^0-9]", "")


def _mod97(m: Column) -> Column:
    """Remainder of an account number with its first four characters moved to the end, letters as 10 to 35."""
    s = F.regexp_replace(m, " ", "")
    s = F.concat(F.substr(s, F.lit(5)), F.substr(s, F.lit(1), F.lit(4)))
    step = lambda a, c: F.when(F.ascii(c) < 58, a * 10 + F.ascii(c) - 48).otherwise(a * 100 + F.ascii(c) - 55) % 97
    return F.aggregate(F.array_remove(F.split(s, "(?!^)"), ""), F.lit(0), step)


def valid(kind: str, m: Column) -> Column:
    if kind == "ip":
        part = lambda p: F.regexp_replace(p, "^0+(?=[0-9])", "")
        return F.forall(F.split(m, r"\."), lambda p: (F.length(part(p)) < 3) | ((F.length(part(p)) == 3) & (part(p) <= "255")))
    if kind == "card":
        return F.length(_digits(m)).between(12, 19) & F.call_function("luhn_check", _digits(m))
    if kind == "phone":
        return F.length(_digits(m)).between(9, 15)
    if kind == "iban":
        return F.length(F.regexp_replace(m, " ", "")).between(15, 34) & (_mod97(m) == 1)
    return F.lit(True)


def _let(value: Column, body: Callable[[Column], Column]) -> Column:
    """A value that an expression uses several times, worked out once."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def _running(values: Column, op: Callable[[Column, Column], Column]) -> Column:
    """For each number of an array the total of those before it, from 0 on."""
    none = F.array().cast("array<int>")

    def short(xs: Column) -> Column:
        begin = F.struct(F.lit(0).alias("t"), none.alias("out"))
        return F.aggregate(xs, begin, lambda a, x: F.struct(op(a["t"], x).alias("t"), F.concat(a["out"], F.array(a["t"])).alias("out")))

    def blocks(xs: Column) -> Column:
        root = F.ceil(F.sqrt(F.size(xs))).cast("int")
        return _let(root, lambda c: F.transform(F.sequence(F.lit(0), F.floor((F.size(xs) - 1) / c).cast("int")), lambda k: short(F.slice(xs, k * c + 1, c))))

    def joined(bs: Column) -> Column:
        before = short(F.transform(bs, lambda b: b["t"]))["out"]
        return _let(before, lambda o: F.flatten(F.transform(bs, lambda b, k: F.transform(b["out"], lambda x: op(F.get(o, k), x)))))

    return F.when(F.size(values) > 0, _let(values, lambda xs: _let(blocks(xs), joined))).otherwise(none)


def _spans(kind: str) -> Column:
    """Array of (s, k, e, kind, score) of one kind, from the held parts and matches."""
    order = KINDS.index(kind)
    parts, found = F.col(f"{kind}_p"), F.col(f"{kind}_m")
    none = F.array().cast("array<struct<s:int,k:int,e:int,kind:string,score:double>>")
    end = lambda c: F.right(c, F.lit(30))

    def span(at: Column, m: Column, i: Column) -> Column:
        before = F.concat(F.coalesce(end(F.get(parts, i - 1)), F.lit("")), F.coalesce(end(F.get(found, i - 1)), F.lit("")), end(F.get(parts, i)))
        # Pattern, validator (where there is one) and context each speak for a span.
        score = F.lit(0.3 if kind == "key" else 0.7) + F.when(F.lower(end(before)).rlike(CONTEXT[kind]), 0.3).otherwise(0.0)
        return F.struct(at.alias("s"), F.lit(order).alias("k"), (at + F.length(m)).alias("e"), F.lit(kind).alias("kind"), score.alias("score"))

    steps = F.transform(found, lambda m, i: F.length(F.get(parts, i)) + F.length(m))
    each = lambda starts: F.transform(found, lambda m, i: F.when(valid(kind, m), span(F.get(starts, i) + F.length(F.get(parts, i)), m, i)))
    all_ = F.when(F.size(found) > 0, F.filter(_let(_running(steps, lambda a, x: a + x), each), lambda x: x.isNotNull())).otherwise(none)
    return all_ if kind in BASE else F.filter(all_, lambda x: x["score"] >= 0.5)


def scan(docs: DataFrame, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The columns keep, text, and spans: an array of (s, k, e, kind, score) by start, then kind."""
    df = docs.select(*[c for c in keep if c != "text"], F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    empty = F.array().cast("array<string>")
    made = {}
    for kind, pattern in PATTERNS.items():
        hint = HINTS[kind](F.col("text"))
        made[f"{kind}_p"] = F.when(hint, F.split("text", pattern, -1)).otherwise(empty)
        made[f"{kind}_m"] = F.when(hint, F.regexp_extract_all("text", F.lit(pattern), F.lit(0))).otherwise(empty)
    df = held(df, **made)
    df = held(df, spans=F.sort_array(F.concat(*[_spans(k) for k in KINDS])))
    return df.drop(*made)


def _listed(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["kind"], x["s"].cast("string"), x["e"].cast("string"))), ",")


def digest(found: DataFrame) -> DataFrame:
    """doc_id, counts of the base kinds, base_sha256, spans, scores."""
    base = F.filter("spans", lambda x: x["k"] < len(BASE))
    of = lambda i: F.size(F.filter("spans", lambda x: x["k"] == i)).cast("long")
    count = [of(i).alias(f"n_{k}") for i, k in enumerate(BASE)]
    scores = F.array_join(F.transform("spans", lambda x: x["score"].cast("decimal(3,1)").cast("string")), ",")
    return found.select(F.col("doc_id").cast("long").alias("doc_id"), *count, F.sha2(_listed(base), 256).alias("base_sha256"), _listed(F.col("spans")).alias("spans"), scores.alias("scores"))


def redact(docs: DataFrame) -> DataFrame:
    """The same columns, with a mark in place of each span, and n_chars of the new text where there is such a column."""
    columns = docs.columns
    own = [x for x, c in zip(apart(docs)[0], columns) if c != "text"]
    found = scan(docs.select(*own, "text"), tuple(f"own__{i}" for i, c in enumerate(columns) if c != "text"))

    def between(chunks: Column, a: Column, b: Column) -> Column:
        """Code points a to b."""
        one, two = (F.floor(x / _CHUNK).cast("int") for x in (a, b))
        head = F.substr(F.coalesce(F.get(chunks, one), F.lit("")), a % _CHUNK + 1, F.when(one == two, b - a).otherwise(F.lit(_CHUNK)))
        middle = F.when(two > one + 1, F.array_join(F.slice(chunks, one + 2, two - one - 1), "")).otherwise("")
        tail = F.when(two > one, F.substr(F.coalesce(F.get(chunks, two), F.lit("")), F.lit(1), b % _CHUNK)).otherwise("")
        return F.concat(head, middle, tail)

    def cleaned(chunks: Column) -> Column:
        reach = _running(F.transform("spans", lambda x: x["e"]), lambda a, x: F.greatest(a, x))
        mark = lambda x, pos: F.when(x["s"] >= pos, F.concat(between(chunks, pos, x["s"]), F.lit("<"), x["kind"], F.lit(">"))).otherwise("")
        pieces = _let(reach, lambda ends: F.transform("spans", lambda x, i: mark(x, F.get(ends, i))))
        return F.concat(F.array_join(pieces, ""), between(chunks, F.array_max(F.transform("spans", lambda x: x["e"])), F.length("text")))

    text = F.when(F.size("spans") > 0, _let(F.regexp_extract_all("text", F.lit(f"(?s).{{1,{_CHUNK}}}+"), F.lit(0)), cleaned)).otherwise(F.col("text"))
    out = held(found, clean=text)
    made = {"text": F.col("clean"), "n_chars": F.length("clean").cast("long")}
    return out.select(*[(made[c] if c in made else F.col(f"own__{i}")).alias(c) for i, c in enumerate(columns)])
