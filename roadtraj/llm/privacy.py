"""Personal data: pattern spans, and terms whose co-occurrence discloses them.

Patterns find the protected entities. A term is a run of letters and digits with a
letter, lower case. Over the whole corpus of N documents, with n(e) and n(t)
documents that hold the entity and the term, and n(e, t) that hold both, the
entity carries log(N / n(e)) of information and the term reveals
log(n(e, t) N / (n(e) n(t))) of it. A term that reveals at least a set share of the
information of an entity is, wherever it stands in a document with that entity, a
span of kind ``term``: generalised to its shape (a code, a name or a word), or
removed where it reveals nearly all. One
document is enough, since most personal values occur in no more. Everything is
built-in DataFrame expressions and SQL functions.

All counts are of whole documents, spans included; only what stands outside every
pattern span is marked. Entities of the same documents have the same shares, and
so have terms of the same documents, so pairs are counted between such classes,
known by a 128-bit sum of hashes. n(e, t) is at most n(e), so pairs whose term is
too frequent for the set share even then are not formed.

Defined results: a null text is empty; a null doc_id is an id of its own;
repeated rows count as documents each and get the same spans; columns beyond
doc_id and text are ignored by ``find``; empty tables give empty tables. The
cost of locating patterns is linear in the matches of one text, folds of
bounded length aside.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from roadtraj.llm.scratch import materialize

# Patterns start only where a run of their first class starts or the last match
# ended, and repeat possessively: one pass over texts of any shape.
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
KINDS = (*PATTERNS, "term")
_MARK = {"email": "@", "phone": "+"}
_VALID = {
    "email": "true",
    "ip": r"forall(split({v}, '\\.'), p -> p rlike '^0*(?:[0-9]{{1,2}}|1[0-9]{{2}}|2[0-4][0-9]|25[0-5])$')",
    "card": "length(regexp_replace({v}, '[^0-9]', '')) BETWEEN 14 AND 19 AND luhn_check(regexp_replace({v}, '[^0-9]', ''))",
    "phone": "length(regexp_replace({v}, '[^0-9]', '')) BETWEEN 10 AND 15",
}
_GAP = r"[^\p{L}\p{N}]+"
_RUN = r"[\p{L}\p{N}]+"

GENERALISE, REMOVE = 0.8, 0.95


_FOLD = 256  # matches that one fold gathers; an array grows by copying


def _located(matches: str, gaps: str, kind: int) -> str:
    """SQL: (start, kind, stop, value) of matches, whose surroundings are the gaps. Folds of bounded length, within one fold."""
    row = "struct<start: int, kind: int, stop: int, value: string>"
    begin = f"b.at + length({gaps}[b.n])"
    inner = (
        f"aggregate(slice({matches}, k * {_FOLD} + 1, {_FOLD}), named_struct('at', a.at, 'n', k * {_FOLD}, 'out', cast(array() as array<{row}>)), "
        f"(b, x) -> named_struct('at', {begin} + length(x), 'n', b.n + 1, 'out', concat(b.out, array(named_struct('start', {begin}, 'kind', {kind}, 'stop', {begin} + length(x), 'value', x)))), "
        f"b -> named_struct('at', b.at, 'out', concat(a.out, array(b.out))))"
    )
    return f"aggregate(sequence(0, cast((size({matches}) - 1) div {_FOLD} as int)), named_struct('at', 0, 'out', cast(array() as array<array<{row}>>)), (a, k) -> {inner}, a -> flatten(a.out))"


def _quoted(pattern: str) -> str:
    return "'" + pattern.replace("\\", "\\\\") + "'"


def base_spans(docs: DataFrame, keep: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, row_key, spans, held: valid pattern matches by start, then kind, and the text of rows that have some."""
    text = F.coalesce(F.col("text"), F.lit(""))
    frame = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("doc_id", "text").alias("row_key"), text.alias("_t"), *keep)
    digits = F.col("_t").rlike("[0-9]")
    lists = []
    for kind, pattern in PATTERNS.items():
        likely = F.contains("_t", F.lit(_MARK[kind])) if kind in _MARK else digits
        frame = frame.withColumn(f"_m_{kind}", F.when(likely, F.regexp_extract_all("_t", F.lit(pattern), F.lit(0))).otherwise(F.expr("cast(array() as array<string>)")))
    for kind, pattern in PATTERNS.items():
        frame = frame.withColumn(f"_g_{kind}", F.when(F.size(f"_m_{kind}") > 0, F.split("_t", pattern, -1)).otherwise(F.expr("cast(array() as array<string>)")))
        located = _located(f"_m_{kind}", f"_g_{kind}", KINDS.index(kind))
        lists.append(f"filter({located}, s -> {_VALID[kind].format(v='s.value')})")
    frame = frame.withColumn("spans", F.expr(f"sort_array(concat({', '.join(lists)}))"))
    return frame.select("doc_id", "row_key", *keep, "spans", F.when(F.size("spans") > 0, F.col("_t")).alias("held"))


def _terms(text: Column) -> Column:
    """The distinct terms of a text."""
    return F.array_distinct(F.transform(F.filter(F.split(text, _GAP, -1), lambda x: (F.length(x) >= 2) & x.rlike(r"\p{L}")), F.lower))


def term_documents(docs: DataFrame) -> DataFrame:
    """term, n_term: the documents that hold each term, over all texts."""
    return docs.select(F.explode(_terms(F.coalesce("text", F.lit("")))).alias("term")).groupBy("term").agg(F.count(F.lit(1)).alias("n_term"))


def _classes(each: DataFrame, what: str) -> DataFrame:
    """what, n, sums: the documents of each value, and sums of their hashes that tell sets of documents apart."""
    halves = [f"sum(copies * {half})" for salt in (0, 1) for half in (f"shiftright(xxhash64({salt}, id, row_key), 32)", f"(xxhash64({salt}, id, row_key) & 4294967295L)")]
    return each.groupBy(what).agg(F.sum("copies").alias("n"), F.expr(f"array({', '.join(halves)})").alias("sums"))


def disclosures(docs: DataFrame, found: DataFrame) -> DataFrame:
    """id, row_key, term, share: the terms of each document that reveal GENERALISE or more of an entity in it, and the most they reveal."""
    total = float(found.count())
    held = found.where("held IS NOT NULL").select(F.coalesce("doc_id", F.lit(-1)).alias("id"), "row_key", F.expr("array_distinct(transform(spans, s -> struct(s.kind as kind, s.value as value)))").alias("entities"), _terms(F.col("held")).alias("terms"))
    held = materialize(held.groupBy("id", "row_key").agg(F.count(F.lit(1)).alias("copies"), F.first("entities").alias("entities"), F.first("terms").alias("terms")), "held")
    each = held.select("id", "row_key", "copies", F.explode("entities").alias("entity"))
    of_entity = materialize(_classes(each, "entity").where(F.col("n") < total), "entities")
    entities = each.join(of_entity, "entity").select("id", "row_key", "copies", F.col("n").alias("n_entity"), F.col("sums").alias("of_entity")).distinct()

    most = of_entity.agg(F.max("n")).first()[0] or 0
    reach = lambda n: F.pow(F.lit(max(total, 1.0)), F.lit(1 - GENERALISE)) * F.pow(n, F.lit(GENERALISE)) * F.lit(1 + 1e-9)
    each = held.select("id", "row_key", "copies", F.explode("terms").alias("term"))
    of_term = _classes(each, "term").drop("n").join(term_documents(docs).where(F.col("n_term") <= reach(F.lit(float(most)))), "term")
    terms = materialize(each.drop("copies").join(materialize(of_term, "classes"), "term").withColumnRenamed("sums", "of_term"), "terms")

    of_doc = terms.select("id", "row_key", "n_term", "of_term").distinct()
    pairs = materialize(entities.join(of_doc, ["id", "row_key"]).where(F.col("n_term") <= reach(F.col("n_entity"))), "pairs")
    kinds = ["n_entity", "of_entity", "n_term", "of_term"]
    share = F.log(F.col("n_both") * F.lit(total) / (F.col("n_entity") * F.col("n_term"))) / F.log(F.lit(total) / F.col("n_entity"))
    flagged = materialize(pairs.groupBy(kinds).agg(F.sum("copies").alias("n_both")).withColumn("share", share).where(F.col("share") >= GENERALISE), "flagged")
    best = pairs.join(flagged, kinds).groupBy("id", "row_key", "n_term", "of_term").agg(F.max("share").alias("share"))
    return terms.join(best, ["id", "row_key", "n_term", "of_term"]).select("id", "row_key", "term", "share")


def _shape(run: Column) -> Column:
    """What a term is generalised to."""
    return F.when(run.rlike(r"\p{N}"), "CODE").when(run.rlike(r"^\p{Lu}"), "NAME").otherwise("WORD")


def _extra(found: DataFrame, flagged: DataFrame) -> DataFrame:
    """id, row_key, extra: every occurrence of the flagged terms of each document that no span overlaps.

    A run ends where the lengths of all runs and gaps up to it add up to. It is
    overlapped if a span that starts before its end ends behind its start.
    """
    rows = found.where("held IS NOT NULL").select(F.coalesce("doc_id", F.lit(-1)).alias("id"), "row_key", "spans", "held")
    rows = rows.join(flagged.select("id", "row_key").distinct(), ["id", "row_key"], "left_semi").dropDuplicates(["id", "row_key"])
    cut = rows.select("id", "row_key", F.split("held", _RUN, -1).alias("gap"), F.regexp_extract_all("held", F.lit(_RUN), F.lit(0)).alias("run"))
    runs = cut.select("id", "row_key", F.posexplode(F.arrays_zip("gap", "run")).alias("pos", "x")).where("x.run IS NOT NULL")
    here = Window.partitionBy("id", "row_key")
    placed = runs.withColumn("stop", F.sum(F.length("x.gap") + F.length("x.run")).over(here.orderBy("pos")).cast("int"))
    placed = placed.select("id", "row_key", F.lower("x.run").alias("term"), _shape(F.col("x.run")).alias("shape"), (F.col("stop") - F.length("x.run")).alias("start"), "stop")
    hits = placed.join(flagged, ["id", "row_key", "term"]).select("id", "row_key", "start", "stop", "share", "shape", (2 * F.col("stop") - 1).alias("at"))
    spans = rows.select("id", "row_key", F.explode("spans").alias("s")).select("id", "row_key", "s.start", "s.stop", F.lit(None).cast("double").alias("share"), F.lit(None).cast("string").alias("shape"), (2 * F.col("s.start")).alias("at"))
    swept = hits.unionByName(spans).withColumn("taken", F.max(F.when(F.col("share").isNull(), F.col("stop"))).over(here.orderBy("at")))
    clear = swept.where(F.col("share").isNotNull() & (F.coalesce("taken", F.lit(0)) <= F.col("start")))
    return clear.groupBy("id", "row_key").agg(F.sort_array(F.collect_list(F.struct("start", F.lit(KINDS.index("term")).alias("kind"), "stop", (F.col("share") >= REMOVE).alias("gone"), "shape"))).alias("extra"))


def find(docs: DataFrame, keep: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, row_key, base and extra spans of each document row.

    ``base``: array of (start, kind, stop) by start, then kind; ``extra``: the
    disclosing terms, with ``gone`` where they are to be removed.
    """
    found = materialize(base_spans(docs, keep), "spans")
    extra = _extra(found, materialize(disclosures(docs, found), "flagged")).withColumnRenamed("id", "_id").withColumnRenamed("row_key", "_key")
    base = found.select("doc_id", "row_key", *keep, F.expr("transform(spans, s -> struct(s.start as start, s.kind as kind, s.stop as stop))").alias("base"))
    joined = base.join(extra, (base["row_key"] == extra["_key"]) & (F.coalesce(base["doc_id"], F.lit(-1)) == extra["_id"]), "left")
    return joined.select("doc_id", "row_key", *keep, "base", F.coalesce("extra", F.expr("cast(array() as array<struct<start: int, kind: int, stop: int, gone: boolean, shape: string>>)")).alias("extra"))


def written(spans: Column) -> Column:
    """Spans as text: kind:start:end, joined by commas."""
    kinds = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(kinds, s["kind"]), s["start"].cast("string"), s["stop"].cast("string"))), ",")


def digests(found: DataFrame) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans."""
    counts = [F.expr(f"cast(size(filter(base, s -> s.kind = {k})) as bigint)").alias(f"n_{kind}") for k, kind in enumerate(PATTERNS)]
    both = F.sort_array(F.concat("base", F.transform("extra", lambda s: F.struct(s["start"], s["kind"], s["stop"]))))
    return found.select("doc_id", *counts, F.sha2(written(F.col("base")), 256).alias("base_sha256"), written(both).alias("spans"))


def sanitise(docs: DataFrame) -> DataFrame:
    """The documents with every span replaced by its kind or shape, or removed; their columns as they came."""
    names = docs.columns
    found = find(docs).dropDuplicates(["doc_id", "row_key"]).withColumnRenamed("doc_id", "_id").withColumnRenamed("row_key", "_key").where((F.size("base") > 0) | (F.size("extra") > 0))
    merged = (
        "aggregate(sort_array(concat(transform(base, s -> named_struct('start', s.start, 'kind', s.kind, 'stop', s.stop, 'gone', false, 'shape', cast(null as string))), extra)), "
        "named_struct('at', 0, 'out', cast(array() as array<string>)), (a, s) -> CASE WHEN s.start < a.at THEN named_struct('at', greatest(a.at, s.stop), 'out', a.out) ELSE "
        "named_struct('at', s.stop, 'out', concat(a.out, array(substring(_t, a.at + 1, s.start - a.at), CASE WHEN s.gone THEN '' ELSE concat('<', coalesce(s.shape, upper(_kinds[s.kind])), '>') END))) END, "
        "a -> concat(array_join(a.out, ''), substring(_t, a.at + 1)))"
    )
    keyed = docs.withColumn("_row", F.xxhash64("doc_id", "text"))
    joined = keyed.join(found, (keyed["_row"] == found["_key"]) & keyed["doc_id"].cast("long").eqNullSafe(found["_id"]), "left")
    clean = joined.withColumn("_t", F.coalesce(docs["text"], F.lit(""))).withColumn("_kinds", F.array(*[F.lit(k) for k in KINDS]))
    clean = clean.withColumn("_clean", F.when(F.col("base").isNull(), docs["text"]).otherwise(F.expr(merged)))
    changed = {"text": F.col("_clean"), "n_chars": F.length("_clean").cast("long")}
    return clean.select(*[changed[c].alias(c) if c in changed else docs[c] for c in names])
