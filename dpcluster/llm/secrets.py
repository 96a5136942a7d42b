"""Secret scans with DataFrame functions only.

Three base patterns give spans: assignments to names such as ``password``, access keys, and long
runs of hex digits.  The method adds candidate strings (runs of key characters) in which some
window has a Shannon entropy above the threshold of the string's character class; every candidate but
one of digits and signs alone has a class.  The entropy
slides: only the counts of the character that enters and the one that leaves are looked up in the window.  Strings on
the allow-list, and those that touch a base span, are not added.

Spans count code points from 0, end exclusive.  Defined results: null text is empty text and has no
spans; repeated rows are scanned each; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Fixed values of the contract: the base patterns.
ASSIGN = r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{16,}"
HEX = r"[0-9a-f]{24,}"
KINDS = ("assign", "access", "hex", "entropy")

CANDIDATE = r"[A-Za-z0-9+/_=-]{20,}"
#: class: pattern of the whole string, window, least entropy in bits
CLASSES = (
    ("hex", r"^[0-9a-fA-F]+$", 24, 2.9),
    ("mixed", r"^(?=.*[a-z])(?=.*[A-Z])(?=.*[0-9]).*$", 20, 3.65),
    ("lower and digits", r"^(?![0-9a-f]+$)(?=.*[a-z])(?=.*[0-9])[^A-Z]+$", 20, 3.7),
    ("upper and digits", r"^(?![0-9A-F]+$)(?=.*[A-Z])(?=.*[0-9])[^a-z]+$", 20, 3.7),
    ("letters of one case", r"^([^A-Z0-9]+|[^a-z0-9]+)$", 20, 3.75),
    ("letters of both", r"^(?=.*[a-z])(?=.*[A-Z])[^0-9]+$", 20, 3.9),
)
#: Slugs, paths and constants of one case, and identifiers in humps: words with a few digits behind, or digits between separators.
SLUGS = r"(?-i:" + "|".join(rf"^/?[{x}]{{1,15}}[0-9]{{0,4}}([/_=+-]+([{x}]{{1,15}}[0-9]{{0,4}}|[0-9]{{1,8}}))+/?$" for x in ("a-z", "A-Z")) + r"|^[a-z]{0,15}([A-Z][a-z]{2,14})+$)"
#: Known harmless strings: digits alone, identifiers in groups, digests of files, dummy values, paths of words.
ALLOW = r"(?i)^[0-9_=+/-]+$|^[0-9a-f]{8}(-[0-9a-f]{4}){3}-[0-9a-f]{12}$|^sha(1|256|384|512)-|example|dummy|placeholder|xxxx|abcdefgh|01234567|^(/?[a-z]{1,15}[/_-])+[a-z0-9]{0,15}$|" + SLUGS


def _once(value: Column, then) -> Column:
    """then(value), with the value computed once a row, however often it is used and whatever lambda it is used in."""
    return F.transform(F.array(value), then)[0]


def _located(text: Column, pattern: str, keep=None) -> Column:
    """Start and end of all matches, from the lengths of what lies between them: the text is not searched again."""
    empty = F.expr("cast(array() as array<struct<s:int,e:int,m:string>>)")
    state = F.struct(F.lit(0).alias("at"), empty.alias("spans"))
    both = F.arrays_zip(F.split(text, pattern, -1).alias("gap"), F.regexp_extract_all(text, F.lit(pattern), F.lit(0)).alias("m"))

    def add(acc: Column, x: Column) -> Column:
        start = acc["at"] + F.length(x["gap"])
        end = start + F.length(x["m"])
        spans = F.array_append(acc["spans"], F.struct(start.alias("s"), end.alias("e"), x["m"].alias("m")))
        fine = x["m"].isNotNull() & keep(x["m"]) if keep else x["m"].isNotNull()
        return F.struct(F.coalesce(end, start).alias("at"), F.when(fine, spans).otherwise(acc["spans"]).alias("spans"))

    return F.aggregate(both, state, add, lambda acc: acc["spans"])


def _part(count: Column) -> Column:
    return F.when(count > 0, count * F.log2(count.cast("double"))).otherwise(0.0)


def _count(window: Column, ch: Column) -> Column:
    return F.length(window) - F.length(F.replace(window, ch, F.lit("")))


def window_entropy(text: Column, width: int) -> Column:
    """The highest entropy in bits over all windows of a string; 0 if it is shorter than the window.

    The state is the sum of count * log2(count) over the characters of the window."""
    state = F.struct(F.lit(0.0).alias("sum"), F.lit(0.0).alias("best"))

    def slide(acc: Column, at: Column) -> Column:
        new = F.substr(text, at, F.lit(1))
        kept = F.substr(text, F.greatest(F.lit(1), at - (width - 1)), F.least(at - 1, F.lit(width - 1)))
        has = _count(kept, new)
        total = acc["sum"] + _part(has + 1) - _part(has)
        best = F.when(at >= width, F.greatest(acc["best"], F.log2(F.lit(float(width))) - total / width)).otherwise(acc["best"])
        old = F.substr(text, at - (width - 1), F.lit(1))
        full = F.substr(text, F.greatest(F.lit(1), at - (width - 1)), F.lit(width))
        goes = _count(full, old)
        after = F.when(at >= width, total + _part(goes - 1) - _part(goes)).otherwise(total)
        return F.struct(after.alias("sum"), best.alias("best"))

    return F.aggregate(F.sequence(F.lit(1), F.greatest(F.length(text), F.lit(1))), state, slide, lambda acc: acc["best"])


def suspicious(text: Column, allow: str = ALLOW, classes=CLASSES) -> Column:
    high = F.lit(False)
    for width in sorted({c[2] for c in classes}):
        own = [F.when(text.rlike(pattern), F.lit(least)) for _, pattern, w, least in classes if w == width]
        least = F.least(*own) if len(own) > 1 else own[0]
        high = high | F.when(least.isNotNull(), window_entropy(text, width) >= least).otherwise(False)
    return ~text.rlike(allow) & high


def _tagged(spans: Column, kind: int) -> Column:
    return F.transform(spans, lambda x: F.struct(x["s"].alias("s"), F.lit(kind).alias("k"), x["e"].alias("e")))


def _said(spans: Column) -> Column:
    names = F.array(*map(F.lit, KINDS))
    return F.array_join(F.transform(F.array_sort(spans), lambda x: F.concat_ws(":", F.element_at(names, x["k"] + 1), x["s"].cast("string"), x["e"].cast("string"))), ",")


def spans(docs: DataFrame, allow: str = ALLOW, classes=CLASSES) -> DataFrame:
    """The documents with their spans: columns __assign, __access, __hex, __entropy beside the others."""
    text = F.coalesce(F.col("text"), F.lit(""))
    long_enough = lambda m: F.length(F.regexp_extract(m, ASSIGN, 2)) >= 6
    base = [_located(text, p, long_enough if k == "assign" else None) for k, p in (("assign", ASSIGN), ("access", ACCESS), ("hex", HEX))]

    def extra(found: Column) -> Column:
        apart = lambda x: ~F.exists(F.concat(*(found[k] for k in KINDS[:3])), lambda b: (b["s"] < x["e"]) & (x["s"] < b["e"]))
        more = F.filter(_located(text, CANDIDATE), lambda x: suspicious(x["m"], allow, classes) & apart(x))
        return F.struct(*(found[k].alias(k) for k in KINDS[:3]), more.alias("entropy"))

    spans_ = _once(F.struct(*(x.alias(k) for k, x in zip(KINDS, base))), extra)
    return docs.withColumn("__spans", spans_).select("*", *(F.col(f"__spans.{k}").alias(f"__{k}") for k in KINDS)).drop("__spans")


def scan(docs: DataFrame, **options) -> DataFrame:
    """Per document: counts of the base kinds, a digest of the base spans, all spans."""
    found = spans(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), **options)
    base = F.concat(*(_tagged(F.col(f"__{k}"), i) for i, k in enumerate(KINDS[:3])))
    every = F.concat(base, _tagged(F.col("__entropy"), 3))
    return found.select(
        "doc_id",
        *(F.size(f"__{k}").cast("long").alias(f"n_{k}") for k in KINDS),
        F.sha2(_said(base), 256).alias("base_sha256"),
        _said(every).alias("spans"),
    )


def redact(docs: DataFrame, mask: str = "[SECRET]", **options) -> DataFrame:
    """The documents with every span replaced; other columns as they were, n_chars counted anew where it is there."""
    found = spans(docs, **options)
    every = F.array_sort(F.concat(*(F.transform(F.col(f"__{k}"), lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"))) for k in KINDS)))
    state = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))

    def put(acc: Column, x: Column) -> Column:
        inside = x["s"] < acc["at"]
        text = F.when(inside, acc["out"]).otherwise(F.concat(acc["out"], F.substr(F.col("text"), acc["at"] + 1, x["s"] - acc["at"]), F.lit(mask)))
        return F.struct(F.greatest(acc["at"], x["e"]).alias("at"), text.alias("out"))

    held = found.withColumn("__every", every)
    clean = F.aggregate(F.col("__every"), state, put, lambda acc: F.concat(acc["out"], F.substr(F.col("text"), acc["at"] + 1, F.length("text"))))
    text = F.when(F.size("__every") > 0, clean).otherwise(F.col("text"))
    out = held.withColumn("text", text)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.size("__every") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars")))
    return out.select(*docs.columns)
