"""Secret scan with multipart linking, in DataFrame functions only.

Strong kinds are reported wherever they stand. Weak parts (identifiers, opaque tokens, endpoints) are reported only when
complementary parts stand in the same scope, at most SCOPE code points between the end of one and the start of the other:
an identifier beside a secret part, an opaque token beside an identifier, an endpoint beside both. The interval join runs
as two windows over the candidates of one document (how far earlier parts reach, where later ones begin), so candidates
are never paired up.

Defined results: null text counts as empty and has no spans; repeated rows are reported once each; extra columns, whatever
their names, are ignored; an empty table gives no rows; texts are read whole.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import with_columns_only
from .spans import add_matches, listed, tagged

KINDS = ("assign", "access", "hex", "ident", "opaque", "endpoint")
SCOPE = 400

# The patterns of the contract, then those of the weak parts.
ASSIGN = r"""(?:(?i:password|passwd|secret|token|api_?key))["']?+\x20*+[:=]\x20*+["']?+([A-Za-z0-9+/_.=-]++)"""
ACCESS = r"AKIA[A-Z0-9]{16,}+"
HEX = r"[0-9a-f]{24,}+"
IDENT = r"""(?i:client|user|account|app|tenant)[_-]?(?i:id|name)["']?+\x20*+[:=]\x20*+["']?+[A-Za-z0-9._@-]{4,}+"""
OPAQUE = r"(?<![A-Za-z0-9+/_-])[A-Za-z0-9+/_-]{20,}+={0,2}+"
ENDPOINT = r"""(?i:https?|jdbc|amqp|redis|mongodb|postgres(?:ql)?)(?::[a-z0-9]++)?+://[^\s"'<>]++"""


def _found(docs: DataFrame) -> DataFrame:
    d = with_columns_only(docs, "doc_id", "text").select(F.col("doc_id").cast("bigint").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    t = F.col("text")
    sign = t.contains(":") | t.contains("=")
    for name, pattern, when in (
        ("assign", ASSIGN, sign),
        ("access", ACCESS, t.contains("AKIA")),
        ("hex", HEX, F.lit(True)),
        ("ident", IDENT, sign),
        ("opaque", OPAQUE, F.lit(True)),
        ("endpoint", ENDPOINT, t.contains("://")),
    ):
        d = add_matches(d, name, "text", pattern, when)
    value = lambda m: F.regexp_extract(m, ASSIGN, 1)
    d = d.withColumn("assign", F.filter("assign", lambda x: F.length(value(x["m"])) >= 6))
    return d.withColumn("opaque", F.filter("opaque", lambda x: x["m"].rlike("[0-9]") & x["m"].rlike("[A-Za-z]")))


def scan(docs: DataFrame, scope: int = SCOPE) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_linked: one row per row of docs."""
    found = _found(docs).select(F.monotonically_increasing_id().alias("rid"), "doc_id", F.concat(*[tagged(k, i) for i, k in enumerate(KINDS)]).alias("all"))
    each = found.select("rid", "doc_id", F.explode_outer("all").alias("x")).select("rid", "doc_id", "x.kind", "x.s", "x.e")
    by = W.partitionBy("rid").orderBy("s")
    before, after = by.rangeBetween(W.unboundedPreceding, 0), by.rangeBetween(0, W.unboundedFollowing)
    strong = F.col("kind") < 3

    def within(*kinds: int) -> Column:
        part = F.col("kind").isin(*kinds)
        reach, begin = F.max(F.when(part, F.col("e"))).over(before), F.min(F.when(part, F.col("s"))).over(after)
        return F.coalesce(reach >= F.col("s") - scope, F.lit(False)) | F.coalesce(begin <= F.col("e") + scope, F.lit(False))

    seen = each.select(
        "*",
        (F.max(F.when(strong, F.col("e"))).over(before) > F.col("s")).alias("under"),
        (F.min(F.when(strong, F.col("s"))).over(after) < F.col("e")).alias("over"),
        within(1, 3).alias("ident_near"),
        within(0, 2, 4).alias("secret_near"),
    )
    clear = ~F.coalesce("under", F.lit(False)) & ~F.coalesce("over", F.lit(False))
    linked = F.when(F.col("kind") == 3, F.col("secret_near")).when(F.col("kind") == 4, F.col("ident_near")).otherwise(F.col("ident_near") & F.col("secret_near"))
    told = seen.withColumn("told", F.when(strong | (clear & linked), F.struct("s", "kind", "e")))
    rows = told.groupBy("rid", "doc_id").agg(F.array_sort(F.collect_list("told")).alias("told"))
    base = F.filter("told", lambda x: x["kind"] < 3)
    count = lambda k: F.size(F.filter("told", lambda x: x["kind"] == k)).cast("bigint")
    return rows.select(
        "doc_id",
        *[count(i).alias(f"n_{KINDS[i]}") for i in range(3)],
        F.sha2(listed(base, KINDS), 256).alias("base_sha256"),
        listed(F.col("told"), KINDS).alias("spans"),
        F.size(F.filter("told", lambda x: x["kind"] >= 3)).cast("bigint").alias("n_linked"),
    )
