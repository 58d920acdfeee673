"""Multipart credential linking, in DataFrame functions only.

Strong parts (assigned passwords and tokens, access key identifiers, long hexadecimal strings) are reported as they
stand. Weak parts (a bare login or key identifier, a token-like string, an endpoint) prove nothing alone: an interval
join within scopes reports them only where a part of another role stands beside them, within reach and without
sharing a character, in the same text. Scopes are blocks of positions as long as the reach; a part stands in every
block that it covers, and a weak part looks into all blocks that its extent and the reach on both sides touch, so the
join stays local however long a text is. Redaction links by the same rule inside the row; it leaves addresses alone
that hold no credential themselves.

Defined results: null text counts as empty; spans are code points, end exclusive; repeated rows are kept apart by a
row number of their own; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from benchvary.session import materialize

# Fixed patterns of the strong kinds: name, pattern, group to measure, least length of that group.
STRONG = (
    ("assign", r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6),
    ("access", r"AKIA[A-Z0-9]+", 0, 20),
    ("hex", r"[0-9a-f]+", 0, 24),
)
# Prefilters that hold for every text with a span of the kind: substrings of which one must occur, then a pattern.
_QUICK = {
    "assign": (("=", ":"), r"(?i)(?:pass|secret|token|api_?key)[a-z]*[\"']?\x20*[:=]"),
    "access": (("AKIA",), None),
    "hex": ((), r"[0-9a-f]{24}"),
    "login": (("=", ":"), r"(?i)(?:user|login|account|client|access)[a-z_]*[\"']?\x20*[:=]"),
    "opaque": ((), r"[A-Za-z0-9+/_-]{32}"),
    "endpoint": (("://",), None),
}
# Weak kinds: name, role, pattern. They count only beside a part of another role.
WEAK = (
    ("login", "identifier", r"""(?i)\b(?:user(?:name)?|login|account|client_?id|access_?key_?id)["']?\x20*[:=]\x20*["']?[A-Za-z0-9._@+-]{3,}"""),
    ("opaque", "secret", r"(?<![A-Za-z0-9+/_=-])(?=[A-Za-z+/_-]*[0-9])(?=[a-z0-9+/_-]*[A-Z])(?=[A-Z0-9+/_-]*[a-z])[A-Za-z0-9+/_-]{32,}={0,2}(?![A-Za-z0-9+/_=-])"),
    ("endpoint", "endpoint", r"""(?:https?|postgres|postgresql|mysql|mongodb|redis|amqp|s3|ftp|ssh)://[^\s"'<>]+"""),
)
ROLE = {"assign": "secret", "access": "identifier", "hex": "secret"} | {k: role for k, role, _ in WEAK}
ORDER = [*(k for k, *_ in STRONG), *(k for k, *_ in WEAK)]
#: Code points between two parts that may belong together.
REACH = 200


def match_spans(text: Column, pattern: str, group: int, least: int) -> Column:
    """Leftmost non-overlapping matches as array<struct<start,end>>, those with a shorter group dropped.

    What stands between the matches and the matches themselves, zipped, give positions as running sums.
    """
    zipped = F.arrays_zip(
        F.transform(F.split(text, pattern, -1), lambda x: F.length(x)).alias("gap"),
        F.transform(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), lambda x: F.length(x)).alias("len"),
        F.transform(F.regexp_extract_all(text, F.lit(pattern), F.lit(group)), lambda x: F.length(x)).alias("own"),
    )
    none = F.array().cast("array<struct<start:int,end:int>>")
    walked = F.aggregate(
        zipped,
        F.struct(F.lit(0).alias("at"), none.alias("found")),
        lambda acc, x: F.struct(
            (acc["at"] + x["gap"] + F.coalesce(x["len"], F.lit(0))).alias("at"),
            F.when(
                x["own"] >= least,
                F.concat(acc["found"], F.array(F.struct((acc["at"] + x["gap"]).alias("start"), (acc["at"] + x["gap"] + x["len"]).alias("end")))),
            )
            .otherwise(acc["found"])
            .alias("found"),
        ),
    )
    return walked["found"]


def _tagged(text: Column, kind: str, pattern: str, group: int, least: int) -> Column:
    """Spans of one kind as array<struct<start,rank,end>>; the costly part runs only for texts that pass the prefilter."""
    none = F.array().cast("array<struct<start:int,rank:int,end:int>>")
    rank = ORDER.index(kind)
    some, quick = _QUICK[kind]
    passes = reduce(lambda a, b: a | b, [F.contains(text, F.lit(x)) for x in some]) if some else F.lit(True)
    if quick:
        passes = passes & text.rlike(quick)
    return F.when(
        passes,
        F.transform(match_spans(text, pattern, group, least), lambda x: F.struct(x["start"].alias("start"), F.lit(rank).alias("rank"), x["end"].alias("end"))),
    ).otherwise(none)


def find_parts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(row_key, doc_id, strong, weak): spans of every text in one scan."""
    text = F.coalesce(F.col("text"), F.lit(""))
    return (
        docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
        .select(
            F.monotonically_increasing_id().alias("row_key"),
            "doc_id",
            F.array_sort(F.concat(*[_tagged(text, k, p, g, n) for k, p, g, n in STRONG])).alias("strong"),
            F.array_sort(F.concat(*[_tagged(text, k, p, 0, 1) for k, _, p in WEAK])).alias("weak"),
        )
    )


def _beside(s: Column, o: Column, reach: int) -> Column:
    """Whether two spans share no character and stand at most reach apart."""
    gap = F.greatest(o["start"] - s["end"], s["start"] - o["end"])
    return (gap >= 0) & (gap <= reach)


def _role(s: Column) -> Column:
    return F.element_at(F.array(*[F.lit(ROLE[k]) for k in ORDER]), s["rank"] + 1)


def _apart(strong: Column, s: Column) -> Column:
    return ~F.exists(strong, lambda b: (b["start"] < s["end"]) & (s["start"] < b["end"]))


def link_parts(parts: DataFrame, reach: int = REACH) -> DataFrame:
    """(row_key, linked): weak spans beside which a part of another role stands; none that touches a strong span."""
    some = parts.where(F.size("weak") > 0)
    s, o = F.col("s"), F.col("o")
    blocks = lambda lo, hi: F.explode(F.sequence(F.floor(lo / reach), F.floor(hi / reach))).alias("scope")
    weak = some.select("row_key", "strong", F.explode("weak").alias("s")).where(_apart(F.col("strong"), s))
    weak = weak.select("row_key", "s", blocks(s["start"] - reach, s["end"] + reach))
    near = some.select("row_key", F.explode(F.concat("strong", "weak")).alias("o")).select("row_key", "o", blocks(o["start"], o["end"] - 1))
    hit = weak.join(near, ["row_key", "scope"]).where((_role(s) != _role(o)) & _beside(s, o, reach))
    return hit.groupBy("row_key").agg(F.array_sort(F.collect_set("s")).alias("linked"))


def linked_in_row(strong: Column, weak: Column, reach: int = REACH) -> Column:
    """What link_parts finds, for one row's own spans."""
    return F.filter(weak, lambda s: _apart(strong, s) & F.exists(F.concat(strong, weak), lambda o: (_role(s) != _role(o)) & _beside(s, o, reach)))


def scan_secrets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", reach: int = REACH) -> DataFrame:
    """(row_key, doc_id, strong, linked): per row of docs the strong spans and the weak spans that found a complement."""
    parts = materialize(find_parts(docs, id_col, text_col), "secret-parts")
    none = F.array().cast("array<struct<start:int,rank:int,end:int>>")
    return parts.select("row_key", "doc_id", "strong").join(link_parts(parts, reach), "row_key", "left").withColumn("linked", F.coalesce("linked", none))


def span_list(spans: Column) -> Column:
    """kind:start:end by start, then kind, joined with commas."""
    names = F.array(*[F.lit(k) for k in ORDER])
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.element_at(names, x["rank"] + 1), x["start"], x["end"])), ",")


#: An address that holds a credential itself: user information, or a parameter that is one.
_TELLING = r"""(?i)://[^/?#\s]*@|[?&;](?:password|passwd|pwd|secret|token|access_?token|api_?key|key|auth|sig|signature)="""


def redact(docs: DataFrame, mark: str = "[secret]", id_col: str = "doc_id", text_col: str = "text", reach: int = REACH) -> DataFrame:
    """docs with every reported span replaced by mark; overlapping spans merge into one, plain addresses stay.

    Spans are found and linked inside the row, so no text is shuffled; the time grows with the square of one text's
    spans. Null texts stay null; repeated rows and empty texts keep their place; columns of any name are kept.
    """
    cols = docs.columns
    text = F.coalesce(F.col(text_col), F.lit(""))
    strong = F.array_sort(F.concat(*[_tagged(text, k, p, g, n) for k, p, g, n in STRONG]))
    weak = F.array_sort(F.concat(*[_tagged(text, k, p, 0, 1) for k, _, p in WEAK]))
    held = "_secret_spans"
    while held in cols:
        held += "_"
    base = docs.withColumn(held, F.struct(strong.alias("strong"), weak.alias("weak")))
    address = ORDER.index("endpoint")
    tells = lambda s: F.substring(F.col(text_col), s["start"] + 1, s["end"] - s["start"]).rlike(_TELLING)
    linked = F.filter(linked_in_row(F.col(held)["strong"], F.col(held)["weak"], reach), lambda s: (s["rank"] != address) | tells(s))
    spans = F.array_sort(F.concat(F.col(held)["strong"], linked))
    edited = F.aggregate(
        spans,
        F.struct(F.lit(0).alias("at"), F.lit("").alias("out")),
        lambda acc, x: F.struct(
            F.greatest(acc["at"], x["end"]).alias("at"),
            F.when(x["start"] >= acc["at"], F.concat(acc["out"], F.substring(F.col(text_col), acc["at"] + 1, x["start"] - acc["at"]), F.lit(mark))).otherwise(acc["out"]).alias("out"),
        ),
        lambda acc: F.concat(acc["out"], F.substring(F.col(text_col), acc["at"] + 1, F.length(F.col(text_col)))),
    )
    return base.withColumn(text_col, F.when(F.size(spans) > 0, edited).otherwise(F.col(text_col))).select(*cols)
