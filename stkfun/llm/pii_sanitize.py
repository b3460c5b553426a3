"""Information-theoretic sanitisation, in DataFrame functions only.

Entities (mail and network addresses, card and phone numbers) are found by
pattern and check. The unit of all counts is the occurrence of a word: N of them
in the corpus, n_t of a term, n_e inside the contexts of an entity (``reach``
characters to either side, within its line, whole words only), n_both of the term
inside them. A term reveals an entity as far as their pointwise mutual
information, log2(n_both N / (n_t n_e)), comes near the most that it can be:
``PMI >= disclosure * log2(N / n_e)``, with at least ``support`` rows in which they
meet. Entities and revealing terms are generalised to their kind (or removed) by
``sanitised``.

A context has a fixed size, so an entity meets no more than ``reach`` words,
however long its line or many its neighbours.

Defined cases: null texts are empty; rows are kept one to one, repeated rows
and null ids included (repeated rows count as documents); texts without an
entity gain no span; an empty table gives an empty result; only the id and text
columns are read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from stkfun.functions.shared import settle, settle_counted
from stkfun.llm.divergence_rules import let

DISCLOSURE = 0.8
SUPPORT = 2
REACH = 80
MAX_TERMS = 200_000

#: The kinds in their order. Runs are possessive and may only
#: start where a run starts (or a match ended), so a search is linear in the
#: text; what they match is the same as without.
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
_NEEDS = {"email": "@", "ip": ".", "phone": "+"}
_WORD = r"[^\x20\x09-\x0D]++"
_SPANS = "array<struct<start:int,end:int,value:string>>"


_STEP = 256


def located(text: Column, pattern: str) -> Column:
    """start, end (code points, end exclusive) and value of all matches.

    Matches are gathered by ``_STEP`` and those arrays joined, so that a text with
    very many does not copy its list for each of them."""

    def walk(p: Column) -> Column:
        def step(acc: Column, i: Column) -> Column:
            start = acc["pos"] + F.length(F.get(p["gaps"], i))
            end = start + F.length(F.get(p["hits"], i))
            one = F.struct(start.alias("start"), end.alias("end"), F.get(p["hits"], i).alias("value"))
            return F.struct(end.alias("pos"), F.concat(acc["out"], F.array(one)).alias("out"))

        def many(acc: Column, k: Column) -> Column:
            zero = F.struct(acc["pos"].alias("pos"), F.array().cast(_SPANS).alias("out"))
            part = F.aggregate(F.sequence(k, F.least(k + _STEP, F.size(p["hits"])) - 1), zero, step)
            return let(part, lambda q: F.struct(q["pos"].alias("pos"), F.concat(acc["out"], q["out"]).alias("out")))

        zero = F.struct(F.lit(0).alias("pos"), F.array().cast(_SPANS).alias("out"))
        return F.when(F.size(p["hits"]) > 0, F.aggregate(F.sequence(F.lit(0), F.size(p["hits"]) - 1, F.lit(_STEP)), zero, many)["out"]).otherwise(F.array().cast(_SPANS))

    parts = F.struct(F.split(text, pattern, -1).alias("gaps"), F.regexp_extract_all(text, F.lit(pattern), F.lit(0)).alias("hits"))
    return let(parts, walk)


def luhn(digits: Column) -> Column:
    """Whether the check digit is right."""
    n = F.length(digits)

    def value(i: Column) -> Column:
        d = F.substring(digits, n - i, F.lit(1)).cast("int")
        twice = d * 2
        return F.when(i % 2 == 0, d).otherwise(F.when(twice > 9, twice - 9).otherwise(twice))

    return F.aggregate(F.transform(F.sequence(F.lit(0), n - 1), value), F.lit(0), lambda a, b: a + b) % 10 == 0


def holds(kind: str, value: Column) -> Column:
    """The check of a match."""
    if kind == "ip":
        trimmed = F.transform(F.split(value, r"\."), lambda p: F.regexp_replace(p, "^0+(?=.)", ""))
        return F.forall(trimmed, lambda p: (F.length(p) <= 3) & (p.cast("int") <= 255))
    digits = F.regexp_replace(value, "[^0-9]", "")
    if kind == "card":
        return F.length(digits).between(12, 19) & let(digits, luhn)
    if kind == "phone":
        return F.length(digits).between(9, 15)
    return F.lit(True)


def entities(text: Column) -> Column:
    """kind, rank, start, end, value of all entities, by start, then kind."""
    shape = "array<struct<start:int,rank:int,kind:string,end:int,value:string>>"

    def of(rank: int, kind: str) -> Column:
        hits = F.filter(located(text, PATTERNS[kind]), lambda s: holds(kind, s["value"]))
        may = F.contains(text, F.lit(_NEEDS[kind])) if kind in _NEEDS else F.rlike(text, F.lit(r"[0-9](?:[\x20-]?[0-9]){11}"))
        tagged = F.transform(hits, lambda s: F.struct(s["start"].alias("start"), F.lit(rank).alias("rank"), F.lit(kind).alias("kind"), s["end"].alias("end"), s["value"].alias("value")))
        return F.when(may, tagged).otherwise(F.array().cast(shape))

    return F.array_sort(F.concat(*[of(rank, kind) for rank, kind in enumerate(PATTERNS)]))


def around(text: Column, found: Column, reach: int = REACH) -> Column:
    """For each entity its name and the two sides of its context, each with the place where it begins."""

    def sides(e: Column) -> Column:
        low = F.greatest(e["start"] - reach - 1, F.lit(0))
        left = F.substring_index(text.substr(low + 1, e["start"] - low), "\n", -1)
        # A word that the reach cuts is left out.
        whole = F.when((low > 0) & (F.length(left) == e["start"] - low), F.regexp_replace(left, r"^[^\x20\x09-\x0D]+", "")).otherwise(left)
        right = F.substring_index(text.substr(e["end"] + 1, F.lit(reach + 1)), "\n", 1)
        until = F.when(F.length(right) > reach, F.regexp_replace(right, r"[^\x20\x09-\x0D]+$", "")).otherwise(right)
        return F.struct(
            F.concat(e["kind"], F.lit(":"), F.lower(e["value"])).alias("entity"),
            F.array(F.struct((e["start"] - F.length(whole)).alias("head"), whole.alias("side")), F.struct(e["end"].alias("head"), until.alias("side"))).alias("sides"),
        )

    return F.transform(found, sides)


def revealing(base: DataFrame, words: DataFrame, n_words: int, disclosure: float, support: int) -> DataFrame:
    """uid, start, end of revealing terms. ``base``: uid, found, contexts of rows with
    entities; ``words``: one row for each of the corpus's ``n_words`` words."""
    near = base.select("uid", "found", F.explode("contexts").alias("l")).select("uid", "found", "l.entity", F.explode("l.sides").alias("s"))
    near = near.select("uid", "entity", "found", "s.head", F.explode(located(F.col("s.side"), _WORD)).alias("w"))
    near = near.select("uid", "entity", F.lower("w.value").alias("term"), (F.col("w.start") + F.col("head")).alias("start"), (F.col("w.end") + F.col("head")).alias("end"), "found")
    near = near.where(~F.exists("found", lambda e: (e["start"] < F.col("end")) & (F.col("start") < e["end"]))).drop("found")
    near = settle(near.distinct(), "nearterms")
    by_row = near.groupBy("entity", "term", "uid").agg(F.count("*").alias("n"))
    together = by_row.groupBy("entity", "term").agg(F.sum("n").alias("n_both"), F.count("*").alias("n_rows")).where(F.col("n_rows") >= support)
    together = settle(together, "together")
    with_entity = near.groupBy("entity").agg(F.count("*").alias("n_entity"))
    terms = together.select("term").distinct()
    # A term has at most REACH characters.
    terms = F.broadcast(terms) if terms.limit(MAX_TERMS + 1).count() <= MAX_TERMS else terms
    with_term = words.join(terms, "term", "left_semi").groupBy("term").agg(F.count("*").alias("n_term"))
    rated = together.join(with_entity, "entity").join(with_term, "term")
    n = F.lit(float(max(n_words, 1)))
    pmi = F.log2(F.col("n_both") * n / (F.col("n_term") * F.col("n_entity").cast("double")))
    told = rated.where((F.col("n_entity") < n) & (pmi >= disclosure * F.log2(n / F.col("n_entity")))).select("entity", "term")
    return near.join(told, ["entity", "term"]).select("uid", "start", "end").distinct()


def personal_spans(docs: DataFrame, disclosure: float = DISCLOSURE, support: int = SUPPORT, reach: int = REACH, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, found (base entities) and terms (start, end of revealing terms) of every row."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    src = docs.select(F.col(id_col).alias("doc_id"), text.alias("t"))
    base = src.select("doc_id", "t", entities(F.col("t")).alias("found"))
    contexts = F.when(F.size("found") > 0, around(F.col("t"), F.col("found"), reach))
    base = base.select(F.monotonically_increasing_id().alias("uid"), "doc_id", "found", contexts.alias("contexts"), F.regexp_count("t", F.lit(_WORD)).cast("long").alias("n_words"))
    base, total = settle_counted(base, "entities", n=F.sum("n_words"))
    words = src.select(F.explode(F.split(F.lower("t"), r"[\x20\x09-\x0D]+")).alias("term"))
    spans = revealing(base.where(F.size("found") > 0), words, total.get("n") or 0, disclosure, support)
    per_row = spans.groupBy("uid").agg(F.array_sort(F.collect_list(F.struct("start", "end"))).alias("terms"))
    return base.join(per_row, "uid", "left").select("doc_id", "found", F.coalesce("terms", F.array().cast("array<struct<start:int,end:int>>")).alias("terms"))


def kind_count(kind: str) -> Column:
    """How many entities of one kind a row has."""
    return F.size(F.filter("found", lambda e: e["kind"] == kind)).cast("long").alias(f"n_{kind}")


def span_list(found: Column) -> Column:
    """kind:start:end of each span, comma-joined."""
    return F.array_join(F.transform(found, lambda e: F.concat_ws(":", e["kind"], e["start"].cast("string"), e["end"].cast("string"))), ",")


def all_spans(found: Column, terms: Column) -> Column:
    """Base spans and revealing terms together, by start, then kind."""
    named = F.transform(terms, lambda s: F.struct(s["start"].alias("start"), F.lit(len(PATTERNS)).alias("rank"), F.lit("term").alias("kind"), s["end"].alias("end")))
    return F.array_sort(F.concat(F.transform(found, lambda e: F.struct(e["start"].alias("start"), e["rank"].alias("rank"), e["kind"].alias("kind"), e["end"].alias("end"))), named))


def sanitised(text: Column, spans: Column, remove: bool = False) -> Column:
    """The text with each span generalised to its kind, or removed."""

    def step(acc: Column, s: Column) -> Column:
        label = F.lit("") if remove else F.concat(F.lit("["), F.upper(s["kind"]), F.lit("]"))
        gap = text.substr(acc["at"] + 1, F.greatest(s["start"] - acc["at"], F.lit(0)))
        ahead = s["start"] >= acc["at"]
        return F.struct(F.greatest(acc["at"], s["end"]).alias("at"), F.when(ahead, F.concat(acc["out"], gap, label)).otherwise(acc["out"]).alias("out"))

    end = F.aggregate(spans, F.struct(F.lit(0).alias("at"), F.lit("").alias("out")), step)
    return let(end, lambda e: F.concat(e["out"], text.substr(e["at"] + 1, F.length(text))))


def op6_query(spark, sf_dir: str) -> DataFrame:
    got = personal_spans(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    counts = [kind_count(k) for k in PATTERNS]
    return got.select("doc_id", *counts, F.sha2(span_list(F.col("found")), 256).alias("base_sha256"), span_list(all_spans(F.col("found"), F.col("terms"))).alias("spans"))
