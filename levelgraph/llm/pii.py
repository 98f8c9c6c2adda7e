"""Personal data by expressions, validators and context, in DataFrame functions only.

Regular expressions propose spans; Luhn, modulo-97, part and digit-count checks confirm them;
words near a span raise or lower its score.  Positions are counted in code points: splitting on
the expression gives the gaps between its matches, so running lengths give every start.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SPAN = "array<struct<start:bigint,end:bigint,hit:string>>"
CONTEXT_CHARS = 40
KEEP_SCORE = 0.5


@dataclass(frozen=True)
class Kind:
    """A kind of personal data: what must occur in a text at all, its expression, and how it is scored."""

    name: str
    guard: str
    expression: str
    base: bool
    prior: float
    context: tuple[str, ...] = ()


# Fixed values.  The first four kinds are the base kinds; possessive groups and the anchors before
# them match the same spans as the plain expressions without backtracking over long runs.  Of an
# IBAN only the head is matched; ``ibans`` finds where it ends.
KINDS = (
    Kind("email", "@", r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]+)++", True, 0.8, ("mail", "email", "contact", "write")),
    Kind("ip", r"[0-9]\.[0-9]", r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]+", True, 0.6, ("ip", "host", "address", "server")),
    Kind("card", "[0-9]", r"[0-9](?:[\x20-]?[0-9])++", True, 0.9, ("card", "visa", "credit", "payment")),
    Kind("phone", r"\+[0-9]", r"\+[0-9][\x20().0-9-]+[0-9]", True, 0.7, ("call", "phone", "tel", "mobile")),
    Kind("iban", "[A-Z]{2}[0-9]{2}", r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?=(?:\x20?[A-Z0-9]){11})", False, 0.8, ("iban", "bank", "account", "transfer")),
    Kind("key", "AKIA", r"(?<![A-Za-z0-9])AKIA[0-9A-Z]{16}(?![A-Za-z0-9])", False, 0.5, ("key", "access", "aws", "secret")),
    Kind("secret", "[0-9a-f]{16}", r"(?<![A-Za-z0-9])[0-9a-f]{16,128}(?![A-Za-z0-9])", False, 0.2, ("token", "password", "secret", "key")),
)
# Characters of an IBAN by country.
IBAN_CHARS = {x[:2]: int(x[2:]) for x in (
    "AD24 AE23 AL28 AT20 AZ28 BA20 BE16 BG22 BH22 BI27 BR29 BY28 CH21 CR22 CY28 CZ24 DE22 DJ27 DK18 DO28 EE20 EG29 ES24 FI18 FK18 FO18 FR27 GB22 GE22 GI23 GL18 GR27 GT28 HN28 HR21 HU28 "
    "IE22 IL23 IQ23 IS26 IT27 JO30 KW30 KZ20 LB28 LC32 LI21 LT20 LU20 LV21 LY25 MC27 MD24 ME22 MK19 MN20 MR27 MT31 MU30 NI28 NL18 NO15 OM23 PK24 PL28 PS29 PT25 QA29 RO24 RS22 RU33 "
    "SA24 SC31 SD18 SE24 SI19 SK24 SM27 SO23 ST25 SV28 TL23 TN24 TR26 UA29 VA22 VG24 XK20 YE30"
).split()}
IBAN_RUN = r"^[A-Z]{2}[0-9]{2}(?:\x20?[A-Z0-9]){11,30}"


def proposed(text: Column, kind: Kind) -> Column:
    """Leftmost non-overlapping matches with their limits in code points."""
    hits = F.regexp_extract_all(text, F.lit(kind.expression), F.lit(0))
    gaps = F.split(text, kind.expression, -1)
    pairs = F.zip_with(hits, F.slice(gaps, F.lit(1), F.size(hits)), lambda h, g: F.struct(h.alias("h"), g.alias("g")))
    start = F.struct(F.lit(0).cast("bigint").alias("at"), F.array().cast(SPAN).alias("out"))

    def step(acc: Column, x: Column) -> Column:
        begin = acc["at"] + F.length(x["g"])
        end = begin + F.length(x["h"])
        span = F.struct(begin.alias("start"), end.alias("end"), x["h"].alias("hit"))
        return F.struct(end.alias("at"), F.concat(acc["out"], F.array(span)).alias("out"))

    found = F.aggregate(pairs, start, step, lambda acc: acc["out"])
    return F.when(text.rlike(kind.guard), found).otherwise(F.array().cast(SPAN))


def luhn(digits: Column) -> Column:
    """Checksum of a string of digits."""
    n = F.length(digits)

    def step(acc: Column, i: Column) -> Column:
        d = F.substring(digits, n - i + 1, F.lit(1)).cast("int")
        twice = d * 2
        return acc + F.when(i % 2 == 0, F.when(twice > 9, twice - 9).otherwise(twice)).otherwise(d)

    return F.aggregate(F.sequence(F.lit(1), n), F.lit(0), step) % 10 == 0


def mod97(code: Column) -> Column:
    """ISO 7064 check of an IBAN: four leading characters moved to the end, letters as 10 to 35."""
    plain = F.replace(code, F.lit(" "), F.lit(""))
    turned = F.concat(F.substring(plain, F.lit(5), F.length(plain)), F.substring(plain, 1, 4))

    def step(acc: Column, i: Column) -> Column:
        v = F.instr(F.lit("0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZ"), F.substring(turned, i, F.lit(1))) - 1
        return F.when(v < 10, acc * 10 + v).otherwise(acc * 100 + v) % 97

    return F.aggregate(F.sequence(F.lit(1), F.length(turned)), F.lit(0), step) == 1


def ibans(text: Column, heads: Column) -> Column:
    """Spans from heads of IBANs to an end that passes the check: the one at the length of the
    country, else the last one; ends stand before anything but a letter or digit.  Spans that begin
    inside the one before are left out."""
    lengths = F.create_map(*[F.lit(x) for item in IBAN_CHARS.items() for x in item])

    def whole(s: Column) -> Column:
        piece = F.substring(text, (s["start"] + 1).cast("int"), F.lit(68))  # 34 characters, spaces between, the next one
        run = F.regexp_extract(piece, IBAN_RUN, 0)
        cut = lambda e: F.substring(run, F.lit(1), e)
        ends = F.filter(F.sequence(F.lit(15), F.greatest(F.length(run), F.lit(15))), lambda e: F.substring(piece, e, F.lit(2)).rlike("^[A-Z0-9](?![A-Za-z0-9])") & (F.length(F.replace(cut(e), F.lit(" "), F.lit(""))) >= 15) & mod97(cut(e)))
        usual = F.filter(ends, lambda e: F.length(F.replace(cut(e), F.lit(" "), F.lit(""))) == lengths[F.substring(run, 1, 2)])
        end = F.coalesce(F.array_max(usual), F.array_max(ends))
        return F.struct(s["start"].alias("start"), (s["start"] + end).alias("end"), F.substring(run, F.lit(1), end).alias("hit"))

    found = F.filter(F.transform(heads, whole), lambda s: s["end"].isNotNull())
    return F.aggregate(found, F.array().cast(SPAN), lambda out, s: F.when(s["start"] < F.coalesce(F.array_max(F.transform(out, lambda o: o["end"])), F.lit(0)), out).otherwise(F.concat(out, F.array(s))))


def confirmed(kind: Kind, hit: Column) -> Column:
    digits = F.regexp_replace(hit, "[^0-9]", "")
    if kind.name == "ip":
        value = lambda p: F.ltrim(p, F.lit("0"))
        return F.forall(F.split(hit, r"\."), lambda p: (F.length(value(p)) <= 3) & (F.coalesce(value(p).try_cast("int"), F.lit(0)) <= 255))
    if kind.name == "card":
        return F.when(F.length(digits).between(14, 19), luhn(digits)).otherwise(False)
    if kind.name == "phone":
        return F.length(digits).between(10, 15)
    return F.lit(True)


def scored(text: Column, kind: Kind, spans: Column) -> Column:
    """Spans that pass, with a score moved by the words before and after them."""
    words = "(?i)(?<![A-Za-z])(?:" + "|".join(kind.context) + ")(?![A-Za-z])"

    def near(s: Column) -> Column:
        lo = F.greatest(s["start"] - CONTEXT_CHARS, F.lit(0))
        before = F.substring(text, (lo + 1).cast("int"), (s["start"] - lo).cast("int"))
        after = F.substring(text, (s["end"] + 1).cast("int"), F.lit(CONTEXT_CHARS))
        helped = before.rlike(words) | after.rlike(words)
        score = F.least(F.lit(1.0), F.lit(kind.prior) + F.when(helped, 0.3).otherwise(0.0))
        return F.struct(s["start"].alias("start"), F.lit(KINDS.index(kind)).alias("rank"), s["end"].alias("end"), F.lit(kind.name).alias("kind"), score.alias("score"))

    if kind.name == "iban":
        spans = ibans(text, spans)
    return F.transform(F.filter(spans, lambda s: confirmed(kind, s["hit"])), near)


def find_personal_data(docs: DataFrame, text: str = "text", keep_score: float = KEEP_SCORE) -> DataFrame:
    """Adds ``personal_data``: spans ``(start, rank, end, kind, score)`` by start, then kind.

    Spans of base kinds stay whatever their score; spans of the other kinds stay from
    ``keep_score`` on.  Null and empty texts have no spans; an empty table gives an empty result and
    repeated rows are searched each.  Limits are code points, end exclusive.  All other columns are
    kept, whatever their names; a column already named ``personal_data`` is replaced.
    """
    names = [c for c in docs.columns if c != "personal_data"]
    rows = docs.select(*[F.col(f"`{c.replace('`', '``')}`").alias(f"c{k}") for k, c in enumerate(names)])
    return _with_spans(rows, f"c{names.index(text)}", keep_score).toDF(*names, "personal_data")


def _with_spans(rows: DataFrame, text: str, keep_score: float = KEEP_SCORE) -> DataFrame:
    """``rows`` (columns named by their place) with ``spans`` at the end."""
    body = F.coalesce(F.col(text).cast("string"), F.lit(""))
    held = [f"of_{k.name}" for k in KINDS]
    out = rows.withColumns({h: proposed(body, k) for h, k in zip(held, KINDS, strict=True)})
    parts = []
    for h, k in zip(held, KINDS, strict=True):
        spans = scored(body, k, F.col(h))
        parts.append(spans if k.base else F.filter(spans, lambda s: s["score"] >= keep_score))
    return out.withColumn("spans", F.array_sort(F.concat(*parts))).drop(*held)


def redact(docs: DataFrame, text: str = "text", mark: str = "<{}>") -> DataFrame:
    """Texts with every found span replaced by a mark of its kind; overlapping spans are cut at the first.

    Null texts become empty; all columns are kept, whatever their names."""
    names = docs.columns
    rows = docs.toDF(*[f"c{k}" for k in range(len(names))])
    column = f"c{names.index(text)}"
    found = _with_spans(rows, column)
    body = F.coalesce(F.col(column).cast("string"), F.lit(""))
    pre, post = mark.split("{}")
    start = F.struct(F.lit(0).cast("bigint").alias("at"), F.lit("").alias("out"))

    def step(acc: Column, s: Column) -> Column:
        gap = F.substring(body, (acc["at"] + 1).cast("int"), F.greatest(s["start"] - acc["at"], F.lit(0)).cast("int"))
        joined = F.concat(acc["out"], gap, F.lit(pre), s["kind"], F.lit(post))
        return F.when(s["start"] < acc["at"], acc).otherwise(F.struct(s["end"].alias("at"), joined.alias("out")))

    done = F.aggregate("spans", start, step, lambda acc: F.concat(acc["out"], F.substring(body, (acc["at"] + 1).cast("int"), F.length(body))))
    return found.withColumn(column, done).drop("spans").toDF(*names)


def _listed(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def op10_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    found = find_personal_data(docs)
    base = [k.name for k in KINDS if k.base]
    spans = F.col("personal_data")
    count = lambda name: F.size(F.filter(spans, lambda s: s["kind"] == name)).cast("long").alias(f"n_{name}")
    return found.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        *(count(name) for name in base),
        F.sha2(_listed(F.filter(spans, lambda s: s["kind"].isin(*base))), 256).alias("base_sha256"),
        _listed(spans).alias("spans"),
        F.coalesce(F.array_max(F.transform(spans, lambda s: s["score"])), F.lit(0.0)).alias("score"),
    )
