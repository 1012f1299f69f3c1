"""Information-theoretic sanitisation of personal data, with DataFrame functions only.

Protected entities are found by four patterns (email, ip, card, phone). All words of the documents that mention an entity
are candidate terms; how strongly a term reveals the entity is its pointwise mutual information over the whole corpus, as
a share of the entity's information content: 1 + log2(P(entity | term)) / log2(1 / P(entity)). A term that occurs with
the entity in two different texts at least (copies of one text are no evidence) is generalised from GENERALISE on and
removed from REMOVE on, in the documents that mention the entity. Document frequencies cover all documents.

Positions are code points. They follow from the pieces between matches, whose lengths are summed in two levels, so long
texts with many matches stay cheap. Patterns are anchored at the start of their runs and possessive where that changes no
match, so the matcher neither recurses nor rescans long runs.

Defined cases: a null or empty text has no spans; rows keep their multiplicity, rows of one id and text share their
result; terms never overlap base spans and are compared in lower case, word by word; an empty table gives an empty result;
a null id is treated like any other id; other columns may have any names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._shared import renamed, settle, settle_last, small

KINDS = ("email", "ip", "card", "phone")
GENERALISE, REMOVE = 0.75, 0.9
#: The base patterns of the contract of op10, see the module's text for their anchors.
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"(?<![0-9])(?<![0-9][\x20-])[0-9](?:[\x20-]?+[0-9]){12,}+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
_PART = r"0*(?:[0-9]{1,2}|1[0-9][0-9]|2[0-4][0-9]|25[0-5])"
WORD = r"\p{L}+"
_SPAN = "array<struct<kind:string,start:int,end:int,value:string>>"
_TERM = "array<struct<kind:string,start:int,end:int,disclosure:double>>"


def _possible(text: Column, kind: str) -> Column:
    """A cheap test that spares most texts the pattern."""
    return {"email": F.instr(text, "@") > 0, "phone": F.instr(text, "+") > 0}.get(kind, F.lit(True))


def _sum(lengths: Column) -> Column:
    return F.aggregate(lengths, F.lit(0), lambda a, x: a + x)


def _with_starts(df: DataFrame, pieces: str, matches: str, into: str, chunk: int = 128) -> DataFrame:
    """Adds the code point at which each match starts. Steps and their sums are columns of their own, so that they are computed once a row."""
    steps, sums = f"__steps_{into}", f"__sums_{into}"
    df = df.withColumn(steps, F.when(F.col(pieces).isNotNull(), F.zip_with(F.slice(pieces, 1, F.size(matches)), matches, lambda p, m: F.length(p) + F.length(m))))
    of_chunks = F.transform(F.sequence(F.lit(0), (F.size(matches) / chunk).cast("int")), lambda c: _sum(F.slice(steps, c * chunk + 1, F.lit(chunk))))
    df = df.withColumn(sums, F.when(F.col(steps).isNotNull(), of_chunks))
    before = lambda i: _sum(F.slice(sums, F.lit(1), (i / chunk).cast("int"))) + _sum(F.slice(steps, (i / chunk).cast("int") * chunk + 1, i % chunk))
    starts = F.transform(matches, lambda _, i: before(i) + F.length(F.get(F.col(pieces), i)))
    return df.withColumn(into, F.when(F.col(sums).isNotNull(), starts)).drop(steps, sums)


def _digits(value: Column) -> Column:
    return F.regexp_replace(value, "[^0-9]", "")


def _luhn(digits: Column) -> Column:
    n = F.length(digits)
    each = F.transform(F.sequence(F.lit(1), n), lambda i: F.when((n - i) % 2 == 1, F.substring(digits, i, F.lit(1)).cast("int") * 2).otherwise(F.substring(digits, i, F.lit(1)).cast("int")))
    return _sum(F.transform(each, lambda d: F.when(d > 9, d - 9).otherwise(d))) % 10 == 0


def _valid(kind: str, value: Column) -> Column:
    if kind == "ip":
        return value.rlike(rf"^(?:{_PART}\.){{3}}{_PART}$")
    if kind == "card":
        d = _digits(value)
        return F.when(F.length(d).between(13, 19), _luhn(d)).otherwise(F.lit(False))
    if kind == "phone":
        return F.length(_digits(value)).between(9, 15)
    return F.lit(True)


def _spans(kind: str, matches: Column, starts: Column) -> Column:
    def span(start: Column, i: Column) -> Column:
        value = F.get(matches, i)
        return F.struct(F.lit(kind).alias("kind"), start.alias("start"), (start + F.length(value)).alias("end"), value.alias("value"))

    return F.coalesce(F.filter(F.transform(starts, span), lambda z: _valid(kind, z["value"])), F.array().cast(_SPAN))


def with_spans(df: DataFrame, text: str, kinds: tuple[str, ...] = KINDS) -> DataFrame:
    """Adds a column per kind with its valid spans: kind, start, end and value."""
    body = F.col(text)
    for kind in kinds:
        pattern = PATTERNS[kind]
        df = df.withColumn(f"m_{kind}", F.when(_possible(body, kind), F.regexp_extract_all(body, F.lit(pattern), F.lit(0))))
        # most texts have no match; only the others are cut into pieces
        df = df.withColumn(f"p_{kind}", F.when(F.size(f"m_{kind}") > 0, F.split(body, pattern, -1)))
        df = _with_starts(df, f"p_{kind}", f"m_{kind}", f"s_{kind}")
        df = df.withColumn(kind, _spans(kind, F.col(f"m_{kind}"), F.col(f"s_{kind}")))
    return df.drop(*[f"{a}_{k}" for k in kinds for a in "mps"])


def _joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda z: F.concat_ws(":", z["kind"], z["start"].cast("string"), z["end"].cast("string"))), ",")


def _entity(z: Column) -> Column:
    """One key for the spellings of an entity."""
    return F.concat_ws(":", z["kind"], F.when(z["kind"] == "email", F.lower(z["value"])).when(z["kind"] == "ip", z["value"]).otherwise(_digits(z["value"])))


def _words(text: Column) -> Column:
    """The distinct words of a text in lower case."""
    return F.array_distinct(F.transform(F.regexp_extract_all(text, F.lit(WORD), F.lit(0)), F.lower))


def base_table(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, key (of id and text), of_text (of the text), spans of the base kinds and the entities they mention; written once and reread."""
    rows = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("body"))
    found = with_spans(rows, "body").withColumn("base", F.concat(*KINDS))
    slim = F.transform("base", lambda z: F.struct(z["kind"].alias("kind"), z["start"].alias("start"), z["end"].alias("end")))
    return settle(found.select("id", F.xxhash64("id", "body").alias("key"), F.xxhash64("body").alias("of_text"), slim.alias("base"), F.array_distinct(F.transform("base", _entity)).alias("entities")))


def disclosing_terms(docs: DataFrame, base: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """key, terms: for every document that mentions an entity, the terms that disclose it, with their disclosure."""
    rows = base.where(F.size("entities") > 0).select("key", "of_text", F.explode("entities").alias("entity"))
    # an entity of one text can have no terms
    counts = settle(rows.groupBy("entity").agg(F.count("*").alias("n_entity"), F.min("of_text").alias("a"), F.max("of_text").alias("b")).where("a <> b").drop("a", "b"))
    said = settle(rows.join(counts.select("entity"), "entity").select("key", "of_text", F.xxhash64("entity").alias("entity")).distinct())
    counts = counts.select(F.xxhash64("entity").alias("entity"), "n_entity")
    documents = docs.count()
    body = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    words = docs.select(F.xxhash64(F.col(id_col), body).alias("key"), body.alias("body"))
    keys = settle(said.select("key").distinct())
    holding = settle(words.join(small(keys, F.lit(16)), "key", "left_semi").select("key", _words(F.col("body")).alias("words")))
    met = said.join(holding, "key").select("key", "of_text", "entity", F.explode("words").alias("term"))
    pairs = met.groupBy("entity", "term").agg(F.count("*").alias("together"), F.min("of_text").alias("a"), F.max("of_text").alias("b")).where("a <> b").drop("a", "b")
    n = F.lit(float(max(documents, 2)))
    content = F.log2(n / F.least(F.col("n_entity"), n - 1))
    pairs = settle(pairs.join(counts, "entity"))
    wanted = pairs.select("term").distinct()
    # counted before the join, so that the join has a row a term and not one a term and document
    frequency = docs.select(F.explode(_words(F.col(text_col).cast("string"))).alias("term")).groupBy("term").agg(F.count("*").alias("n_term")).join(wanted, "term")
    share = F.least(F.lit(1.0), F.col("together") / F.col("n_term"))
    strong = pairs.join(frequency, "term").withColumn("disclosure", 1 + F.log2(share) / content).where(F.col("disclosure") >= GENERALISE)
    strong = settle(strong.select("entity", "term", "disclosure"))
    # the terms that a document has, not all those of its entities
    per = met.select("key", "entity", "term").join(strong, ["entity", "term"]).groupBy("key", "term").agg(F.max("disclosure").alias("disclosure"))
    return settle(per.groupBy("key").agg(F.map_from_entries(F.collect_list(F.struct("term", "disclosure"))).alias("terms")))


def _bytes(terms: str) -> Column:
    return F.lit(64) + F.coalesce(F.aggregate(F.map_keys(terms), F.lit(0), lambda a, t: a + F.length(t) * 4 + 24), F.lit(0))


def _term_spans(df: DataFrame, text: str) -> DataFrame:
    """Adds term_spans: where the document's terms stand as whole words outside base spans."""
    body = F.col(text)
    df = df.withColumn("m", F.when(F.col("terms").isNotNull(), F.regexp_extract_all(body, F.lit(WORD), F.lit(0)))).withColumn("p", F.when(F.size("m") > 0, F.split(body, WORD, -1)))
    df = _with_starts(df, "p", "m", "s")
    worth = lambda i: F.try_element_at(F.col("terms"), F.lower(F.get(F.col("m"), i)))
    spans = F.transform("s", lambda x, i: F.struct(F.lit("term").alias("kind"), x.alias("start"), (x + F.length(F.get(F.col("m"), i))).alias("end"), worth(i).alias("disclosure")))
    known = F.filter(spans, lambda z: z["disclosure"].isNotNull())
    clear = F.filter(known, lambda z: ~F.exists(F.col("base"), lambda b: (b["start"] < z["end"]) & (z["start"] < b["end"])))
    return df.withColumn("term_spans", F.coalesce(clear, F.array().cast(_TERM))).drop("m", "p", "s")


def found(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, base (spans) and term_spans of every document."""
    base = base_table(docs, id_col, text_col)
    terms = disclosing_terms(docs, base, id_col, text_col)
    terms = small(terms, _bytes("terms"))
    rows = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("body")).withColumn("key", F.xxhash64("id", "body"))
    holding = _term_spans(rows.join(terms, "key").join(base.select("key", "base").dropDuplicates(["key"]), "key"), "body").select("key", "term_spans").dropDuplicates(["key"])
    return base.join(holding, "key", "left").select(F.col("id").alias(id_col), "base", F.coalesce("term_spans", F.array().cast(_TERM)).alias("term_spans"))


def report(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The columns of the contract of op10."""
    spans = found(docs, id_col, text_col)

    def count(kind: str) -> Column:
        return F.size(F.filter("base", lambda z: z["kind"] == kind)).cast("long").alias(f"n_{kind}")

    everything = F.concat("base", F.transform("term_spans", lambda z: F.struct(z["kind"].alias("kind"), z["start"].alias("start"), z["end"].alias("end"))))
    return spans.select(id_col, *map(count, KINDS), F.sha2(_joined(F.col("base")), 256).alias("base_sha256"), _joined(everything).alias("spans"), F.size("term_spans").cast("long").alias("n_term"))


def sanitised(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with personal data replaced by its kind, disclosing terms generalised or removed; n_chars, where there, follows."""

    inner, names = renamed(docs)
    text, id_ = names[text_col], names[id_col]

    def spans_and_terms() -> DataFrame:
        base = base_table(inner, id_, text)
        return base.where(F.size("base") > 0).select("key", "base").dropDuplicates(["key"]).join(disclosing_terms(inner, base, id_, text), "key", "left")

    wanted = settle_last(spans_and_terms)
    wanted = small(wanted, _bytes("terms") + F.size("base") * 48)
    marked = inner.withColumn("__body", F.coalesce(F.col(text).cast("string"), F.lit(""))).withColumn("key", F.xxhash64(F.col(id_), F.col("__body")))
    rows = _term_spans(marked.join(wanted, "key", "left").withColumn("base", F.coalesce("base", F.array().cast("array<struct<kind:string,start:int,end:int>>"))), "__body")
    word = lambda z: F.when(z["disclosure"] >= REMOVE, F.lit("")).when(F.substring(F.col("__body"), z["start"] + 1, F.lit(1)).rlike(r"\p{Lu}"), F.lit("[NAME]")).otherwise(F.lit("[WORD]"))
    kind = "array<struct<start:int,end:int,by:string>>"
    named = F.transform("base", lambda z: F.struct(z["start"].alias("start"), z["end"].alias("end"), F.concat(F.lit("["), F.upper(z["kind"]), F.lit("]")).alias("by")))
    rows = rows.withColumn("cuts", F.when(F.size("base") > 0, F.sort_array(named)))
    # overlapping spans of several kinds become one, named by the first; terms overlap nothing
    merge = F.aggregate(
        "cuts",
        F.array().cast(kind),
        lambda out, z: F.when((F.size(out) > 0) & (F.get(out, F.size(out) - 1)["end"] > z["start"]), F.concat(F.slice(out, F.lit(1), F.size(out) - 1), F.array(F.struct(F.get(out, F.size(out) - 1)["start"].alias("start"), F.greatest(F.get(out, F.size(out) - 1)["end"], z["end"]).alias("end"), F.get(out, F.size(out) - 1)["by"].alias("by"))))).otherwise(F.concat(out, F.array(z))),
    )
    touching = F.exists(F.sequence(F.lit(1), F.size("cuts") - 1), lambda i: F.get("cuts", i - 1)["end"] > F.get("cuts", i)["start"])
    merge = F.when(F.size("cuts") < 2, F.col("cuts")).when(touching, merge).otherwise(F.col("cuts"))
    rows = rows.withColumn("cuts", F.when(F.col("cuts").isNotNull(), merge))
    replaced = F.transform("term_spans", lambda z: F.struct(z["start"].alias("start"), z["end"].alias("end"), word(z).alias("by")))
    rows = rows.withColumn("cuts", F.when(F.col("cuts").isNotNull(), F.sort_array(F.concat("cuts", replaced))))
    body, cut = F.col("__body"), F.col("cuts")
    piece = F.transform(cut, lambda z, i: F.concat(F.substring(body, F.coalesce(F.get(cut, i - 1)["end"], F.lit(0)) + 1, z["start"] - F.coalesce(F.get(cut, i - 1)["end"], F.lit(0))), z["by"]))
    last = F.get(cut, F.size(cut) - 1)["end"]
    rewritten = F.concat(F.array_join(piece, ""), F.substring(body, last + 1, F.length(body)))
    rows = rows.withColumn(text, F.when(cut.isNotNull(), rewritten).otherwise(F.col(text)))
    if "n_chars" in docs.columns:
        n = names["n_chars"]
        rows = rows.withColumn(n, F.when(cut.isNotNull(), F.length(text).cast("long")).otherwise(F.col(n)))
    return rows.select(*[F.col(n).alias(c) for c, n in names.items()])
