"""Personal data spans from regular expressions, checksums and context words.

Everything is a DataFrame expression.  For each kind the text is split at the
matches, which gives the text before and after each match and, through running
lengths, its position in code points.  All patterns use possessive loops and
look-behind guards, so matching is linear and needs no recursion on long runs.

Base kinds (email, ip, card, phone) are kept when their check passes.  Further
kinds (iban, secret, ssn) are scored: a pattern has a prior, a passed checksum
and a context word within ``WINDOW`` code points raise it, and the span is kept
from ``THRESHOLD`` on.  An account number is found by its head alone; its end is
the country's, or for a country without a known length the last end of a word
where the checksum passes, so text after it is never taken for a part of it.
Null text counts as empty; empty text has no spans; ties of start go by kind.
Repeated rows are treated one by one; no row is lost or joined.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WINDOW = 40
THRESHOLD = 0.6

_OCTET = r"0*+(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9][0-9]|[0-9]|)"

#: kind -> (cheap test on the text, pattern, prior, context words).  The order
#: is the order of kinds at equal starts.
KINDS = {
    "email": ("@", r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++", 0.9, r"mail|contact|write"),
    "ip": (r"[0-9]\.[0-9]", r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++", 0.8, r"host|server|\bip\b|address"),
    "card": (r"[0-9][\x20-]?[0-9]", r"(?<![0-9])(?<![0-9][\x20-])[0-9](?:[\x20-]?[0-9]){11,18}+(?![\x20-]?[0-9])", 0.3, r"card|visa|credit|pay"),
    "phone": (r"\+[0-9]", r"\+[0-9][\x20().0-9-]+[0-9]", 0.7, r"phone|call|tel|mobile|fax"),
    "iban": (r"[A-Z]{2}[0-9]{2}", r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?=((?:\x20?[A-Z0-9]){11,30}+[A-Za-z0-9]?))", 0.3, r"iban|bank|account|konto"),
    "secret": (r"[=:]\x20?[\x22']", r"(?<![A-Za-z0-9_])(?:[Tt]oken|[Pp]assword|[Ss]ecret|[Aa]pi_?[Kk]ey)\x20?[=:]\x20?[\x22'][^\x22'\n]{8,}+[\x22']", 0.7, r"key|token|login|auth"),
    "ssn": (r"[0-9]-[0-9]", r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])", 0.3, r"ssn|social|security|tax"),
}
#: Registered lengths of account numbers: length -> countries.
IBAN_LENGTHS = {
    15: "NO", 16: "BE", 18: "DK FI FK FO GL NL SD", 19: "MK SI", 20: "AT BA EE KZ LT LU MN XK", 21: "CH HR LI LV",
    22: "BG BH CR DE GB GE IE ME RS VA", 23: "AE GI IL IQ OM SO TL", 24: "AD CZ ES MD PK RO SA SE SK TN VG", 25: "LY PT ST",
    26: "IS TR", 27: "BI DJ FR GR IT MC MR SM", 28: "AL AZ BY CY DO GT HN HU LB NI PL SV", 29: "BR EG PS QA UA",
    30: "JO KW MU YE", 31: "MT SC", 32: "LC", 33: "RU",
}
BASE = ("email", "ip", "card", "phone")


def _digits(match: Column) -> Column:
    return F.regexp_replace(match, "[^0-9]", "")


def _mod97(match: Column) -> Column:
    """Whether an account number's rearranged digits leave 1 modulo 97."""
    plain = F.replace(match, F.lit(" "))
    turned = F.concat(F.substr(plain, F.lit(5)), F.substring(plain, 1, 4))
    step = lambda acc, c: (
        F.when(c.between("0", "9"), (acc * 10 + F.ascii(c) - 48) % 97).otherwise((acc * 100 + F.ascii(c) - 55) % 97)
    )
    return F.aggregate(F.split(turned, ""), F.lit(0), lambda acc, c: F.when(c == "", acc).otherwise(step(acc, c)).cast("int")) == 1


def _tail_length(head: Column, tail: Column) -> Column:
    """Characters of ``tail`` that belong to the account number begun by
    ``head``; null if it is none."""
    lengths = F.create_map(*[F.lit(x) for n, names in IBAN_LENGTHS.items() for c in names.split() for x in (c, n)])
    known = F.try_element_at(lengths, F.left(head, F.lit(2)))

    def ends(k: Column) -> Column:
        part = F.left(tail, k)
        return (
            part.rlike(r"^(?:\x20?[A-Z0-9]){11,30}$")
            & ~F.substr(tail, k + 1, F.lit(1)).rlike("[A-Za-z0-9]")
            & F.coalesce(F.length(F.replace(part, F.lit(" "))) + 4 == known, F.lit(True))
            & _mod97(F.concat(head, part))
        )

    return F.array_max(F.filter(F.sequence(F.lit(11), F.length(tail)), ends))


def _valid(kind: str, match: Column) -> Column:
    """The checksum or range test of a kind; true where it has none."""
    if kind == "ip":
        return match.rlike(rf"^(?:{_OCTET}\.){{3}}{_OCTET}$")
    if kind == "card":
        return F.length(_digits(match)).between(12, 19) & F.call_function("luhn_check", _digits(match))
    if kind == "phone":
        return F.length(_digits(match)).between(9, 15)
    if kind == "ssn":
        return ~match.rlike(r"^(?:000|666|9)|-00-|-0000$")
    return F.lit(True)


def _prefix(values: Column) -> Column:
    """Sums of the values before each position.

    Done in runs of about the square root of the length, so the work on a text
    with k matches grows as k to the power 1.5, not as its square.
    """
    run = F.greatest(F.lit(1), F.sqrt(F.size(values)).cast("int"))
    total = lambda part: F.aggregate(part, F.lit(0), lambda a, x: a + x)
    runs = F.transform(F.sequence(F.lit(0), ((F.size(values) - 1) / run).cast("int")), lambda r: total(F.slice(values, r * run + 1, run)))
    heads = F.transform(runs, lambda _, r: total(F.slice(runs, F.lit(1), r)))
    return F.flatten(
        F.transform(heads, lambda head, r: F.transform(F.slice(values, r * run + 1, run), lambda _, i: head + total(F.slice(values, r * run + 1, i))))
    )


def _spans(kind: str) -> Column:
    """Spans of one kind from its split pieces and matches."""
    _, _, prior, context = KINDS[kind]
    pieces, matches, widths = F.col(f"pieces_{kind}"), F.col(f"matches_{kind}"), F.col(f"widths_{kind}")
    start = lambda i: F.get(F.col(f"starts_{kind}"), i) + F.length(F.get(pieces, i))

    def span(match: Column, i: Column) -> Column:
        tail = F.get(F.col("tails_iban"), i) if kind == "iban" else F.lit(0)
        after = F.substr(F.get(pieces, i + 1), F.coalesce(tail, F.lit(0)) + 1, F.lit(WINDOW))
        near = F.concat(F.right(F.get(pieces, i), F.lit(WINDOW)), F.lit(" "), after)
        score = F.lit(prior) + F.when(F.lower(near).rlike(context), 0.3).otherwise(0.0)
        if kind in ("card", "iban"):
            score = score + 0.4
        return F.struct(
            start(i).alias("start"),
            F.lit(list(KINDS).index(kind)).alias("rank"),
            (start(i) + F.length(match) + F.coalesce(tail, F.lit(0))).alias("end"),
            F.least(F.lit(1.0), score).alias("score"),
            (tail.isNotNull() if kind == "iban" else _valid(kind, match)).alias("valid"),
        )

    kept = F.filter(F.transform(matches, span), lambda s: s["valid"] if kind in BASE else s["valid"] & (s["score"] >= THRESHOLD))
    return F.when(F.size(widths) > 0, kept).otherwise(F.filter(F.transform(matches, span), lambda s: F.lit(False)))


def pii_spans(docs: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """``keep`` columns and ``spans``: array of (start, end, kind, score), by
    start and then kind.  Positions are code points, ends exclusive."""
    df = docs.select(*keep, F.coalesce(F.col(text), F.lit("")).alias("pii_text"))
    body = F.col("pii_text")
    cuts = []
    for kind, (mark, pattern, _, _) in KINDS.items():
        test = body.rlike(mark)
        none = F.array().cast("array<string>")
        cuts += [
            F.when(test, F.regexp_extract_all(body, F.lit(pattern), F.lit(0))).otherwise(none).alias(f"matches_{kind}"),
            F.when(test, F.split(body, pattern, -1)).otherwise(none).alias(f"pieces_{kind}"),
        ]
        if kind == "iban":
            cuts.append(F.when(test, F.regexp_extract_all(body, F.lit(pattern), F.lit(1))).otherwise(none).alias("after_iban"))
    df = df.select(*keep, *cuts)
    df = df.withColumn("tails_iban", F.zip_with("matches_iban", "after_iban", _tail_length))
    for kind in KINDS:
        widths = F.zip_with(F.slice(F.col(f"pieces_{kind}"), F.lit(1), F.size(f"matches_{kind}")), F.col(f"matches_{kind}"), lambda p, m: F.length(p) + F.length(m))
        df = df.withColumn(f"widths_{kind}", F.when(F.size(f"matches_{kind}") > 0, widths).otherwise(F.array().cast("array<int>")))
    for kind in KINDS:
        empty = F.array().cast("array<int>")
        df = df.withColumn(f"starts_{kind}", F.when(F.size(f"widths_{kind}") > 0, _prefix(F.col(f"widths_{kind}"))).otherwise(empty))
    df = df.select(*keep, F.array_sort(F.concat(*map(_spans, KINDS))).alias("found"))
    names = F.array(*map(F.lit, KINDS))
    shaped = F.transform("found", lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), F.get(names, s["rank"]).alias("kind"), s["score"].alias("score")))
    return df.select(*keep, shaped.alias("spans"))


def span_digest(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def pii_report(docs: DataFrame) -> DataFrame:
    """The digest of ``pii_spans``: counts, a hash of the base spans, all spans."""
    df = pii_spans(docs)
    base = F.filter("spans", lambda s: s["kind"].isin(*BASE))
    count = lambda kind: F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    return df.select(
        "doc_id",
        *map(count, KINDS),
        F.sha2(span_digest(base), 256).alias("base_sha256"),
        span_digest(F.col("spans")).alias("spans"),
        F.coalesce(F.array_max(F.transform("spans", lambda s: s["score"])), F.lit(0.0)).alias("top_score"),
    )
