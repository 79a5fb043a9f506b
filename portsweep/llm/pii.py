"""Personal data, and the terms that give it away, in DataFrame functions only.

Base kinds (email, ip, card, phone) are found by pattern. Their values are the protected entities; so that entities of one
or two documents are also judged by what recurs, the account and the domain of an email and the network of an ip (its first
three numbers) are entities too. How strongly a term of a document with an entity reveals it is measured over the corpus:
with N documents, of which e hold the entity, t the term and b both, all by their whole texts, the pointwise mutual
information log(N b / (e t)) is compared with the entity's information content log(N / e). A term is disclosing if it
reaches ALPHA of that; an entity of every document has none and is disclosed by nothing. All occurrences of a disclosing
term in the documents that hold the entity are sanitised: words are removed (the mark [TERM] stays in their place), numbers
are generalised to [NUMBER]. Entities held by the same documents have the same measures and are counted as one.

Terms are counted before they meet the entities' terms, so every join here is one row per term, entity or document.

Defined results: null text counts as empty and has no spans; rows that repeat another's doc_id and text get the same
result and count as one document; extra columns, whatever their names, are ignored by scan and kept by sanitise; an empty
table gives no rows; texts are read whole.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import BROADCAST_BYTES, fresh, materialize, with_columns_only
from .spans import add_matches, listed, tagged

KINDS = ("email", "ip", "card", "phone", "term", "number")
ALPHA, SUPPORT = 0.8, 1

# The patterns of the contract, anchored so that each run of characters is tried once.
EMAIL = r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"
IP = r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++"
CARD = r"[0-9](?:[\x20-]?[0-9]){15,}+"
PHONE = r"\+[0-9][\x20().0-9-]+[0-9]"
TERM = r"[\p{L}\p{N}]++"


def _digits(x: Column) -> Column:
    return F.regexp_replace(x, "[^0-9]", "")


def _luhn(d: Column) -> Column:
    """Luhn's sum of a digit string is a multiple of ten."""

    def step(a: Column, i: Column) -> Column:
        x = F.substring(d, F.length(d) - i + 1, F.lit(1)).cast("int") * F.when(i % 2 == 0, 2).otherwise(1)
        return a + F.when(x > 9, x - 9).otherwise(x)

    return F.aggregate(F.sequence(F.lit(1), F.length(d)), F.lit(0), step) % 10 == 0


def _small(x: Column) -> Column:
    bare = F.regexp_replace(x, "^0+(?=[0-9])", "")
    return (F.length(bare) <= 3) & (F.substring(bare, 1, 3).cast("int") <= 255)


def _base(d: DataFrame) -> DataFrame:
    """d (text, never null) with column base: array of (kind, s, e, m), by kind, then start."""
    t = F.col("text")
    for name, pattern, when in (
        ("email", EMAIL, t.contains("@")),
        ("ip", IP, t.rlike(r"[0-9]\.[0-9]")),
        ("card", CARD, t.rlike("[0-9][\\x20-]?[0-9][\\x20-]?[0-9][\\x20-]?[0-9][\\x20-]?[0-9]")),
        ("phone", PHONE, t.contains("+")),
    ):
        d = add_matches(d, name, "text", pattern, when)
    d = d.withColumn("ip", F.filter("ip", lambda x: F.forall(F.split(x["m"], r"\."), _small)))
    d = d.withColumn("card", F.filter("card", lambda x: F.when(F.length(_digits(x["m"])).between(16, 19), _luhn(_digits(x["m"]))).otherwise(False)))
    d = d.withColumn("phone", F.filter("phone", lambda x: F.length(_digits(x["m"])).between(8, 15)))
    return d.withColumn("base", F.concat(*[tagged(k, i) for i, k in enumerate(KINDS[:4])])).drop(*KINDS[:4])


def _key(text: Column) -> Column:
    """128 bits that name a doc_id with a text."""
    return F.struct(F.xxhash64(F.col("doc_id"), text).alias("a"), F.xxhash64(F.lit(7), text, F.col("doc_id")).alias("b"))


def _keyed(docs: DataFrame) -> DataFrame:
    """doc_id, text (null as empty) and `__k`."""
    text = F.coalesce("text", F.lit(""))
    return with_columns_only(docs, "doc_id", "text").select("doc_id", text.alias("text"), _key(text).alias("__k"))


def _entities(x: Column) -> Column:
    """The entity of a base span, and the wider ones it belongs to."""
    m, kind = F.lower(x["m"]), x["kind"]
    parts = F.split(m, "[@.]")
    own = F.xxhash64(kind, F.when(kind < 2, m).otherwise(_digits(m)))
    account, domain = F.xxhash64(F.lit("account"), F.regexp_extract(m, "^[^@]*", 0)), F.xxhash64(F.lit("domain"), F.regexp_extract(m, "[^@]*$", 0))
    network = F.xxhash64(F.lit("network"), F.concat_ws(".", F.slice(parts, 1, 3)))
    return F.when(kind == 0, F.array(own, account, domain)).when(kind == 1, F.array(own, network)).otherwise(F.array(own))


def _found(d: DataFrame) -> DataFrame:
    """k, doc_id, base spans of (kind, s, e), entities, and the text if there are any."""
    base = _base(d.select("__k", "doc_id", "text"))
    bare = F.transform("base", lambda x: F.struct(x["kind"].alias("kind"), x["s"].alias("s"), x["e"].alias("e")))
    entities = F.array_distinct(F.flatten(F.transform("base", _entities)))
    return base.select("__k", F.col("doc_id").cast("bigint").alias("doc_id"), bare.alias("base"), entities.alias("entities"), F.when(F.size("base") > 0, F.col("text")).alias("held"))


def _placed(near: DataFrame) -> DataFrame:
    """k, term, kind, s, e: all terms of texts `held`, places being sums of the lengths of gaps and terms before them."""
    words, gaps = F.regexp_extract_all("held", F.lit(TERM), F.lit(0)), F.transform(F.split("held", TERM, -1), lambda g: F.length(g))
    each = near.withColumn("__w", words).select("__k", F.posexplode(F.arrays_zip(F.col("__w").alias("m"), F.slice(gaps, 1, F.size("__w")).alias("g"))).alias("i", "w"))
    e = F.sum(F.col("w.g") + F.length("w.m")).over(W.partitionBy("__k").orderBy("i")).cast("int")
    kind = F.when(F.col("w.m").rlike(r"^\p{N}+$"), 5).otherwise(4)
    return each.select("__k", F.xxhash64(F.lower("w.m")).alias("term"), kind.alias("kind"), (e - F.length("w.m")).alias("s"), e.alias("e"))


def disclosing(found: DataFrame, d: DataFrame, alpha: float = ALPHA, support: int = SUPPORT) -> DataFrame:
    """k, terms (array of spans of kinds 4 and 5): occurrences of disclosing terms in the documents of the entities they disclose."""
    near = found.where(F.size("base") > 0).groupBy("__k").agg(F.first("held").alias("held"), F.first("entities").alias("entities"))
    near = materialize(near, "near")
    placed = materialize(_placed(near), "terms")
    holds = near.select("__k", F.explode("entities").alias("entity"))
    mark = F.xxhash64("__k", F.lit(1))
    by_entity = holds.groupBy("entity").agg(F.count("*").alias("e_docs"), F.bit_xor(mark).alias("h1"), F.bit_xor(F.xxhash64("__k", F.lit(2))).alias("h2"))
    alike = by_entity.select("entity", "e_docs", F.xxhash64("e_docs", "h1", "h2").alias("alike"))
    holds = materialize(holds.join(alike, "entity").select("__k", "alike", "e_docs").distinct(), "holds")
    pairs = placed.select("__k", "term").distinct().join(holds, "__k")
    both = materialize(pairs.groupBy("alike", "e_docs", "term").agg(F.count("*").alias("b_docs")).where(F.col("b_docs") >= support), "joint")
    every = d.select(F.explode(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit(TERM), F.lit(0)))).alias("m")).select(F.xxhash64("m").alias("term"))
    counts = every.groupBy("term").agg(F.count("*").alias("t_docs"))  # a row per term of the corpus, added up before it is shuffled
    total = d.agg(F.count("*").alias("n"))
    told = both.join(counts, "term").crossJoin(F.broadcast(total)).where("n > e_docs")  # one row
    pmi = F.log2(F.col("n") * F.col("b_docs") / (F.col("e_docs") * F.col("t_docs")))
    told = materialize(told.where(pmi >= alpha * F.log2(F.col("n") / F.col("e_docs"))).select("alike", "term"), "told")
    hits = pairs.join(told, ["alike", "term"]).select("__k", "term").distinct()
    spans = placed.join(hits, ["__k", "term"])
    return spans.groupBy("__k").agg(F.collect_list(F.struct("kind", "s", "e")).alias("terms"))


def _spans(docs: DataFrame, alpha: float, support: int) -> DataFrame:
    """k, doc_id, all (array of (kind, s, e) by kind, then start): one row per row of docs."""
    d = _keyed(docs)
    found = materialize(_found(d), "pii")
    if found.groupBy("__k").agg(F.count("*").alias("n")).where("n > 1").limit(1).count():
        d = d.dropDuplicates(["__k"])
    terms = disclosing(found, d, alpha, support).withColumnRenamed("__k", "__t")
    clear = F.filter("terms", lambda t: ~F.exists("base", lambda b: (b["s"] < t["e"]) & (t["s"] < b["e"])))
    joined = found.join(terms, F.col("__k") == F.col("__t"), "left")
    return joined.select("__k", "doc_id", F.array_sort(F.concat("base", F.coalesce(clear, F.expr("cast(array() as array<struct<kind:int,s:int,e:int>>)")))).alias("all"))


def scan(docs: DataFrame, alpha: float = ALPHA, support: int = SUPPORT) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_terms: one row per row of docs."""
    rows = _spans(docs, alpha, support)
    count = lambda k: F.size(F.filter("all", lambda x: x["kind"] == k)).cast("bigint")
    return rows.select(
        "doc_id",
        *[count(i).alias(f"n_{KINDS[i]}") for i in range(4)],
        F.sha2(listed(F.filter("all", lambda x: x["kind"] < 4), KINDS), 256).alias("base_sha256"),
        listed(F.col("all"), KINDS).alias("spans"),
        (count(4) + count(5)).alias("n_terms"),
    )


def _rewritten(text: Column, spans: Column) -> Column:
    """text with each span, in order of start, as a mark of its kind; overlapping spans become one mark."""
    marks = F.array(*[F.lit(f"[{k.upper()}]") for k in KINDS])

    def step(a: Column, x: Column) -> Column:
        more = F.concat(a["out"], F.substring(text, a["at"] + 1, x["s"] - a["at"]), F.element_at(marks, x["kind"] + 1))
        return F.struct(F.greatest(a["at"], x["e"]).alias("at"), F.when(x["s"] >= a["at"], more).otherwise(a["out"]).alias("out"))

    start = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))
    ordered = F.array_sort(F.transform(spans, lambda x: F.struct(x["s"].alias("s"), x["kind"].alias("kind"), x["e"].alias("e"))))
    return F.aggregate(ordered, start, step, lambda a: F.concat(a["out"], F.substring(text, a["at"] + 1, F.length(text))))


def sanitise(docs: DataFrame, alpha: float = ALPHA, support: int = SUPPORT) -> DataFrame:
    """docs with protected entities and disclosing terms replaced in text, n_chars set anew; rows and other columns stay."""
    key, spans_of = fresh(docs.columns, "__s", "__all")
    spans = _spans(docs, alpha, support).where(F.size("all") > 0).select(F.col("__k").alias(key), "all").groupBy(key).agg(F.first("all").alias(spans_of))
    spans = materialize(spans, "pii-spans")
    rows, held = spans.agg(F.count("*"), F.sum(F.size(spans_of))).first()
    if rows * 96 + (held or 0) * 48 <= BROADCAST_BYTES:
        spans = F.broadcast(spans)
    text = F.coalesce("text", F.lit(""))
    joined = docs.join(spans, _key(text) == F.col(key), "left")
    done = joined.withColumn("text", F.when(F.col(spans_of).isNull(), text).otherwise(_rewritten(text, F.col(spans_of))))
    if "n_chars" in docs.columns:
        done = done.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return done.select(*[F.col(f"`{c}`") for c in docs.columns])
