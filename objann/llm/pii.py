"""Personal data: base patterns, and terms that reveal it by corpus co-occurrence (operator 3).

DataFrame functions only.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from objann.llm.shared import read_table, scratch, text_or_empty, written

# The kinds in their order, the added kind last.
KINDS = ["email", "ip", "card", "phone", "term"]

# The base patterns.  Quantifiers that cannot give anything back are possessive, and a match may
# begin only where a run begins or the last match ended: the same matches in linear time and
# without recursion.
EMAIL = r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"
IP = r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++"
CARD = r"[0-9](?:[ -]?+[0-9])++"
PHONE = r"\+[0-9][ ().0-9-]+[0-9]"
BYTE = r"0*(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])"

# A word of the context: letters with their marks, with apostrophes and hyphens inside it; quotes and
# brackets around it do not matter.
WORD = r"(?<![\p{L}\p{M}\p{N}_])\p{L}[\p{L}\p{M}]++(?:['\u2019-]\p{L}[\p{L}\p{M}]*+)*+(?![\p{L}\p{M}\p{N}_])"
WINDOW = 96  # code points of context on each side of a span
RESIDUE = 2.0  # bits about an entity that a term must leave open to be harmless
DISCLOSURE = 0.5  # share of an entity's information from which a term can be revealing at all
MAX_BROADCAST_ROWS = 100_000


def _located(gaps: Column, matches: Column, base: Column, kind: int) -> Column:
    """array<struct(start, kind, end, value)> of matches, from the pieces of text between them."""
    sizes = F.zip_with(F.slice(gaps, 1, F.size(matches)), matches, lambda g, m: F.struct(F.length(g).alias("gap"), F.length(m).alias("size"), m.alias("value")))
    empty = F.expr("cast(array() as array<struct<start:int,kind:int,end:int,value:string>>)")

    def step(acc: Column, x: Column) -> Column:
        start = acc["at"] + x["gap"]
        item = F.struct(start.alias("start"), F.lit(kind).alias("kind"), (start + x["size"]).alias("end"), x["value"].alias("value"))
        return F.struct((start + x["size"]).alias("at"), F.concat(acc["found"], F.array(item)).alias("found"))

    return F.aggregate(sizes, F.struct(base.cast("int").alias("at"), empty.alias("found")), step, lambda acc: acc["found"])


def _digits(value: Column) -> Column:
    return F.regexp_replace(value, "[^0-9]", "")


def with_base_spans(df: DataFrame, text: str = "text", into: str = "base") -> DataFrame:
    """``df`` with the base spans of all kinds, by start and then kind: array<struct(start, kind, end, value)>.

    Positions count code points, ends are exclusive.  Null text has none.
    """
    whole = text_or_empty(text)
    likely = [F.contains(whole, F.lit("@")), whole.rlike(r"[0-9]\.[0-9]++\.[0-9]++\.[0-9]"), whole.rlike(r"[0-9](?:[ -]?[0-9]){11}"), whole.rlike(r"\+[0-9]")]
    none = F.expr("cast(array() as array<string>)")
    columns = {}
    for k, (pattern, guard) in enumerate(zip((EMAIL, IP, CARD, PHONE), likely)):
        columns[f"__m{k}"] = F.when(guard, F.regexp_extract_all(whole, F.lit(pattern), F.lit(0))).otherwise(none)
        columns[f"__g{k}"] = F.when(guard, F.split(whole, pattern, -1)).otherwise(none)
    fine = [
        lambda x: F.lit(True),
        lambda x: x["value"].rlike(rf"^{BYTE}(?:\.{BYTE}){{3}}$"),
        lambda x: F.length(_digits(x["value"])).between(12, 19) & F.call_function("luhn_check", _digits(x["value"])),
        lambda x: F.length(_digits(x["value"])).between(9, 15),
    ]
    found = df.withColumns(columns)
    spans = [F.filter(_located(F.col(f"__g{k}"), F.col(f"__m{k}"), F.lit(0), k), fine[k]) for k in range(4)]
    return found.withColumn(into, F.array_sort(F.concat(*spans))).drop(*columns)


def span_text(spans: Column) -> Column:
    """``kind:start:end`` of each span, comma-joined."""
    kinds = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.element_at(kinds, x["kind"] + 1), x["start"].cast("string"), x["end"].cast("string"))), ",")


def _windows(found: DataFrame) -> DataFrame:
    """One row for each base span of each different text: (text_hash, rows, base, start, end, entity, left, right)."""
    once = found.where(F.size("base") > 0).groupBy("text_hash").agg(F.count("*").alias("rows"), F.first("contexts").alias("contexts"), F.first("base").alias("base"))
    return once.select("text_hash", "rows", "base", F.explode("contexts").alias("c")).select("text_hash", "rows", "base", "c.*")


def _terms(windows: DataFrame) -> DataFrame:
    """(text_hash, rows, entity, context, term, start, end): words of the windows that touch no base span."""
    sides = windows.withColumns(
        {
            "left_words": F.regexp_extract_all("left", F.lit(WORD), F.lit(0)),
            "left_gaps": F.split("left", WORD, -1),
            "right_words": F.regexp_extract_all("right", F.lit(WORD), F.lit(0)),
            "right_gaps": F.split("right", WORD, -1),
        }
    )
    left_at = F.col("start") - F.length("left")
    left = F.filter(_located(F.col("left_gaps"), F.col("left_words"), left_at, 4), lambda x: (x["start"] > F.col("start") - F.length("left")) | (F.length("left") < WINDOW))
    right = F.filter(_located(F.col("right_gaps"), F.col("right_words"), F.col("end"), 4), lambda x: (x["end"] < F.col("end") + WINDOW))
    free = F.filter(F.concat(left, right), lambda x: ~F.exists("base", lambda b: (b["start"] < x["end"]) & (b["end"] > x["start"])))
    found = sides.select("text_hash", "rows", "entity", F.xxhash64("left", "right").alias("context"), F.explode(free).alias("t"))
    return found.select("text_hash", "rows", "entity", "context", F.lower("t.value").alias("term"), F.col("t.start").alias("start"), F.col("t.end").alias("end"))


def revealing_terms(df: DataFrame, found: DataFrame, text: str) -> DataFrame:
    """(text_hash, added): spans of terms that give away an entity they stand by.

    Word occurrences of the whole corpus are the probability space.  With c the occurrences of
    a term in windows of an entity, n its occurrences anywhere and m the different contexts
    behind c, the chance that the term speaks of the entity is estimated as c / n, shrunk to
    m / (m + 1) of it, so that one sighting counts half and copies of a text prove nothing more.  The term
    is revealing if that leaves at most RESIDUE bits open and, with w the words in the entity's
    windows and N all words, gives at least DISCLOSURE of the log2(N / w) bits that the entity has.
    So an entity that occurs once is covered as well: a word of its window found nowhere else, or
    once elsewhere, gives it away.  A revealing term is marked wherever it stands in that entity's
    windows.  The rule is in bits of the entity, so it is the same at every corpus size.
    """
    near = written(_terms(_windows(found)), "pii-terms")
    pairs = near.groupBy("entity", "term", "context").agg(F.sum("rows").alias("c")).groupBy("entity", "term").agg(F.sum("c").alias("c"), F.count("*").alias("contexts"))
    pairs = written(pairs, "pii-pairs")
    words = df.select(F.explode(F.regexp_extract_all(F.lower(text_or_empty(text)), F.lit(WORD), F.lit(0))).alias("term"))
    counts = written(words.groupBy("term").agg(F.count("*").alias("n")), "pii-words")
    total = F.lit(float(counts.agg(F.sum("n")).first()[0] or 0))
    weight = pairs.groupBy("entity").agg(F.sum("c").alias("w"))
    scored = pairs.join(counts, "term").join(weight, "entity")
    # overlapping windows of one entity can count an occurrence twice
    chance = F.least(F.lit(1.0), F.col("c") / F.col("n")) * F.col("contexts") / (F.col("contexts") + 1)
    told = F.log2(chance * total / F.col("w")) / F.log2(total / F.col("w"))
    marked = written(scored.where((F.col("w") < total) & (F.log2(chance) >= -RESIDUE) & (told >= DISCLOSURE)).select("entity", "term"), "pii-marked")
    spans = near.join(marked, ["entity", "term"]).select("text_hash", F.struct("start", F.lit(4).alias("kind"), "end", F.lit("").alias("value")).alias("span"))
    return written(spans.groupBy("text_hash").agg(F.collect_set("span").alias("added")), "pii-added", lasting=True)


def find_spans(df: DataFrame, key: str = "doc_id", text: str = "text") -> tuple[DataFrame, DataFrame]:
    """(rows of (id, text_hash, base), rows of (text_hash, added)) as written tables."""
    slim = df.select(F.col(key).alias("id"), text_or_empty(text).alias("text"))
    spans = with_base_spans(slim, "text")
    entity = lambda x: F.concat_ws(":", x["kind"].cast("string"), F.lower(F.when(x["kind"] >= 2, _digits(x["value"])).otherwise(x["value"])))
    contexts = F.transform(
        "base",
        lambda x: F.struct(
            x["start"].alias("start"),
            x["end"].alias("end"),
            entity(x).alias("entity"),
            F.substring(F.col("text"), F.greatest(x["start"] - WINDOW, F.lit(0)) + 1, F.least(x["start"], F.lit(WINDOW))).alias("left"),
            F.substring(F.col("text"), x["end"] + 1, F.lit(WINDOW)).alias("right"),
        ),
    )
    found = spans.select("id", F.sha2("text", 256).alias("text_hash"), "base", contexts.alias("contexts"))
    found = written(found, "pii-found", lasting=True)
    with scratch():
        return found.drop("contexts"), revealing_terms(slim, found, "text")


def personal_data(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, n_email, n_ip, n_card, n_phone, base_sha256, spans) of every row.

    Null and empty texts have no spans.  Equal texts have equal spans; repeated rows repeat; an
    empty table gives no rows; other columns are left out.  Counts are partial aggregates and the
    joins read written tables on both sides, so hot texts, entities and terms are split.
    """
    found, added = find_spans(df, key, text)
    joined = found.join(added, "text_hash", "left")
    spans = F.array_sort(F.concat("base", F.coalesce("added", F.expr("cast(array() as array<struct<start:int,kind:int,end:int,value:string>>)"))))
    count = lambda k: F.size(F.filter("base", lambda x: x["kind"] == k)).cast("long")
    return joined.select(
        F.col("id").alias(key), *[count(k).alias(f"n_{KINDS[k]}") for k in range(4)], F.sha2(span_text(F.col("base")), 256).alias("base_sha256"), span_text(spans).alias("spans")
    )


def sanitise(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``df`` with every span of its text generalised to its kind in brackets; null text stays null.

    Spans that overlap become one, named by the first, so no part of any stays.  Spans of revealing terms come by a join on the text's
    hash, broadcast up to MAX_BROADCAST_ROWS texts.
    """
    _, added = find_spans(df, key, text)
    few = added.limit(MAX_BROADCAST_ROWS + 1).count() <= MAX_BROADCAST_ROWS
    added = added.select(F.col("text_hash").alias("__hash"), F.col("added").alias("__added"))
    spans = with_base_spans(df.withColumn("__text", text_or_empty(text)), "__text", "__base").withColumn("__hash", F.sha2("__text", 256))
    joined = spans.join(F.broadcast(added) if few else added, "__hash", "left")
    everything = F.array_sort(F.concat("__base", F.coalesce("__added", F.expr("cast(array() as array<struct<start:int,kind:int,end:int,value:string>>)"))))
    names = F.array(*[F.lit(f"[{k.upper()}]") for k in KINDS])

    def step(acc: Column, x: Column) -> Column:
        kept = F.concat(acc["out"], F.substring(F.col("__text"), acc["at"] + 1, x["start"] - acc["at"]), F.element_at(names, x["kind"] + 1))
        merged = F.struct(F.greatest(acc["at"], x["end"]).alias("at"), acc["out"].alias("out"))
        return F.when(x["start"] < acc["at"], merged).otherwise(F.struct(x["end"].alias("at"), kept.alias("out")))

    start = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))
    end = lambda acc: F.concat(acc["out"], F.substring(F.col("__text"), acc["at"] + 1, F.length("__text")))
    clean = F.when(F.col(text).isNull(), F.col(text)).when(F.size("__all") == 0, F.col("__text")).otherwise(F.aggregate("__all", start, step, end))
    out = joined.withColumn("__all", everything)
    return out.select(*[clean.alias(c) if c == text else F.col(f"`{c}`") for c in df.columns])


def op3_pii(spark, sf_dir: str) -> DataFrame:
    return personal_data(read_table(spark, sf_dir, "documents"))
