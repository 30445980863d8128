"""Operator 3: information-theoretic sanitisation of personal data, in built-in expressions only.

Protected entities are the e-mail addresses, IP addresses, card and phone numbers that patterns find. For every word
that stands near an entity (within ``near`` code points, and before the next match of its kind), corpus counts give the disclosure ratio: the pointwise mutual information of word and
entity over the information content of the entity, which is 1 where the word occurs nowhere else. Words above the
removal threshold are removed, words above the generalisation threshold are replaced by their shape, and words with
too few joint occurrences to estimate are left. A word that discloses is marked wherever it stands, in every text, near
an entity or not. Pattern spans always stay.

Defined results: null and empty texts have no spans; repeated rows are each given the spans of their text; positions
are code points, the end exclusive; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from packsum.llm.runtime import materialize
from packsum.llm.textexpr import let, word_array, word_count

# Kinds in order, what a match looks like, and what must be in a text that can hold one. Possessive
# repeats and the start condition keep long runs of one character class linear; they change no match.
LOCAL = "A-Za-z0-9._%+-"
KINDS = ("email", "ip", "card", "phone")
PATTERNS = {
    "email": rf"(?:\G|(?<![{LOCAL}]))[{LOCAL}]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++(?:\.[0-9]++){3}",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
GATES = {"email": "@", "ip": r"[0-9]\.[0-9]+\.[0-9]", "card": r"[0-9][\x20-]?[0-9][\x20-]?[0-9]", "phone": r"\+[0-9]"}
BYTE_PART = "0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9])"
LETTERS = r"\p{L}\p{M}"
TERM = rf"(?<=[\x20\x09-\x0D])[{LETTERS}]{{3,}}+(?=[.,;:!?]*[\x20\x09-\x0D])"
WORD = rf"(?<![^\x20\x09-\x0D])[{LETTERS}]{{3,}}+(?=[.,;:!?]*(?:[\x20\x09-\x0D]|\z))"
SPAN = "array<struct<start:int,kind:int,end:int,value:string,near:array<string>>>"
#: Items that a fold takes between copies of what it has gathered.
BLOCK = 256


@dataclass(frozen=True)
class Disclosure:
    near: int = 60  # code points on either side of an entity
    least_joint: int = 3
    generalise: float = 0.85
    remove: float = 0.95
    broadcast_rows: int = 20_000


def luhn(digits: Column) -> Column:
    n = F.length(digits)
    at = lambda i: F.substring(digits, n - i + 1, F.lit(1)).cast("int")
    doubled = lambda d: F.when(d > 4, 2 * d - 9).otherwise(2 * d)
    return F.aggregate(F.sequence(F.lit(1), n), F.lit(0), lambda t, i: t + F.when(i % 2 == 0, doubled(at(i))).otherwise(at(i))) % 10 == 0


def holds(kind: str, match: Column) -> Column:
    if kind == "email":
        return F.lit(True)
    if kind == "ip":
        return match.rlike(rf"^{BYTE_PART}(?:\.{BYTE_PART}){{3}}$")
    digits = F.regexp_replace(match, "[^0-9]", "")
    low, high = (14, 19) if kind == "card" else (10, 15)
    return let(digits, lambda d: F.length(d).between(low, high) & (luhn(d) if kind == "card" else F.lit(True)))


def in_blocks(items: Column) -> Column:
    """An array as an array of runs of ``BLOCK``, so that what a fold grows is copied once a run and not once an item."""
    runs = F.sequence(F.lit(0), F.floor((F.size(items) - 1) / BLOCK).cast("int"))
    return F.when(F.size(items) > 0, F.transform(runs, lambda i: F.slice(items, i * BLOCK + 1, BLOCK))).otherwise(F.array(F.slice(items, 1, 0)))


def places(steps: Column) -> Column:
    """Places of the kept steps as an array of "start:end" strings in order; a step is a match, what lies before it, and
    whether it is kept.

    Running lengths give places. They are gathered in one string, which grows in place of an array.
    """

    def step(a: Column, x: Column) -> Column:
        start = a["pos"] + F.length(x["b"])
        end = start + F.length(x["m"])
        place = F.concat_ws(":", start.cast("string"), end.cast("string"))
        return F.struct(end.alias("pos"), F.when(x["k"], F.concat(a["out"], F.lit(","), place)).otherwise(a["out"]).alias("out"))

    def block(a: Column, steps: Column) -> Column:
        own = F.aggregate(steps, F.struct(a["pos"].alias("pos"), F.lit("").alias("out")), step)
        return let(own, lambda r: F.struct(r["pos"].alias("pos"), F.concat(a["out"], r["out"]).alias("out")))

    joined = F.aggregate(in_blocks(steps), F.struct(F.lit(0).alias("pos"), F.lit("").alias("out")), block, lambda a: a["out"])
    return F.filter(F.split(joined, ","), lambda p: p != "")


def spans_of(text: Column, number: int, near: int) -> Column:
    """Spans of a kind, each with its value and the words within reach, up to the next match of the kind.

    Splitting by the pattern gives what lies between matches. A word counts where it is whole: inside its reach, or up to
    the text's own ends.
    """
    kind = KINDS[number]
    between, matches = F.split(text, PATTERNS[kind], -1), F.regexp_extract_all(text, F.lit(PATTERNS[kind]), F.lit(0))
    words = lambda chunk: F.transform(F.regexp_extract_all(chunk, F.lit(TERM), F.lit(0)), F.lower)

    def steps(m: Column, b: Column, n: Column) -> Column:
        every = F.arrays_zip(m.alias("m"), F.slice(b, 1, n).alias("b"), F.slice(b, 2, n).alias("a"))

        def seen(x: Column, i: Column) -> Column:
            left = F.when(F.length(x["b"]) > near, F.right(x["b"], F.lit(near))).otherwise(F.concat(F.when(i == 0, F.lit(" ")).otherwise(F.lit("")), x["b"]))
            right = F.when(F.length(x["a"]) > near, F.left(x["a"], F.lit(near))).otherwise(F.concat(x["a"], F.when(i == n - 1, F.lit(" ")).otherwise(F.lit(""))))
            keep = holds(kind, x["m"])
            return F.struct(x["m"].alias("m"), x["b"].alias("b"), keep.alias("k"), F.when(keep, F.concat(words(left), words(right))).alias("near"))

        return F.transform(every, seen)

    def spans(found: Column) -> Column:
        def span(place: Column, x: Column) -> Column:
            part = F.split(place, ":")
            return F.struct(part.getItem(0).cast("int").alias("start"), F.lit(number).alias("kind"), part.getItem(1).cast("int").alias("end"), x["m"].alias("value"), x["near"].alias("near"))

        return F.zip_with(places(found), F.filter(found, lambda x: x["k"]), span)

    gate = F.contains(text, F.lit("@")) if kind == "email" else text.rlike(GATES[kind])
    found = let(matches, lambda m: let(between, lambda b: let(F.size(m), lambda n: steps(m, b, n))))  # each computed once a text
    return F.when(gate, let(found, spans)).otherwise(F.array().cast(SPAN))


def base_spans(text: Column, near: int) -> Column:
    return F.sort_array(F.concat(*(spans_of(text, i, near) for i in range(len(KINDS)))))


def entity(span: Column) -> Column:
    value = F.when(span["kind"] >= 2, F.regexp_replace(span["value"], "[^0-9]", "")).otherwise(F.lower(span["value"]))
    return F.concat_ws(":", span["kind"].cast("string"), value)


def spotted(docs: DataFrame, how: Disclosure, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Entities of every row, each with the words near it."""
    own = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    return own.select("doc_id", F.xxhash64("text").alias("tkey"), base_spans(F.col("text"), how.near).alias("base"))


def plain_words(text: Column) -> Column:
    """Words in lower case, without the punctuation that ends them."""
    return F.transform(word_array(text), lambda w: F.lower(F.rtrim(w, F.lit(".,;:!?"))))


def few_rows(df: DataFrame, how: Disclosure) -> bool:
    return df.limit(how.broadcast_rows + 1).count() <= how.broadcast_rows


def disclosing(found: DataFrame, docs: DataFrame, how: Disclosure, text: str = "text") -> DataFrame:
    """(entity, term, ratio) of words that tell too much."""
    told = found.select(F.explode("base").alias("s")).select(entity(F.col("s")).alias("entity"), "s.near")
    joint = told.select("entity", F.explode("near").alias("term")).groupBy("entity", "term").agg(F.count(F.lit(1)).alias("joint")).filter(F.col("joint") >= how.least_joint)
    joint = materialize(joint)
    mentions = materialize(told.groupBy("entity").agg(F.count(F.lit(1)).alias("mentions")))  # on its own, so that a join by an entity met everywhere can be split
    wanted = joint.select("term").distinct()
    tokens = docs.select(F.explode(plain_words(F.col(text))).alias("term"))
    if few_rows(wanted, how):  # the checked side is small; otherwise counts are summed before they meet it
        totals = tokens.join(F.broadcast(wanted), "term").groupBy("term").agg(F.count(F.lit(1)).alias("total"))
    else:
        totals = tokens.groupBy("term").agg(F.count(F.lit(1)).alias("total")).join(wanted, "term")
    size = docs.agg(F.coalesce(F.sum(word_count(F.col(text))), F.lit(0)).alias("n")).first()["n"] + 2  # words of all texts
    rated = joint.join(totals, "term").join(mentions, "entity")
    ratio = 1 + F.log2(F.least(F.lit(1.0), F.col("joint") / F.col("total"))) / F.log2(F.greatest(F.lit(float(size)) / F.col("mentions"), F.lit(2.0)))
    return rated.select("entity", "term", ratio.alias("ratio")).filter(F.col("ratio") >= how.generalise)


def term_spans(docs: DataFrame, told: DataFrame, how: Disclosure, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Per distinct row: all places of disclosing words, in whole texts, near an entity or not.

    Only texts that hold such a word are cut into words with places; places are running lengths, a window in each text.
    """
    terms = materialize(told.groupBy("term").agg(F.max("ratio").alias("ratio")))
    small = lambda df: F.broadcast(df) if few_rows(df, how) else df
    checked = small(terms)
    own = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text")).withColumn("tkey", F.xxhash64("text"))
    words = own.select("doc_id", "tkey", F.explode(plain_words(F.col("text"))).alias("term"))
    holders = materialize(words.join(checked, "term").select(F.col("doc_id").alias("h_id"), F.col("tkey").alias("h_key")).distinct())
    held = own.join(small(holders), F.col("doc_id").eqNullSafe(F.col("h_id")) & (F.col("tkey") == F.col("h_key"))).dropDuplicates(["doc_id", "tkey"])
    matches, between = F.regexp_extract_all("text", F.lit(WORD), F.lit(0)), F.split("text", WORD, -1)
    cut = held.select("doc_id", "tkey", F.posexplode(F.arrays_zip(matches.alias("m"), F.slice(between, 1, F.size(matches)).alias("b"))).alias("at", "x"))
    sofar = Window.partitionBy("doc_id", "tkey").orderBy("at").rowsBetween(Window.unboundedPreceding, 0)
    end = F.sum(F.length("x.b") + F.length("x.m")).over(sofar).cast("int")
    places = cut.select("doc_id", "tkey", F.lower("x.m").alias("term"), (end - F.length("x.m")).alias("start"), end.alias("end"))
    hit = places.join(checked, "term")
    return hit.groupBy(F.col("doc_id").alias("t_id"), F.col("tkey").alias("t_key")).agg(F.sort_array(F.collect_list(F.struct("start", F.lit(len(KINDS)).alias("kind"), "end", "ratio"))).alias("told"))


def sanitised_spans(docs: DataFrame, how: Disclosure = Disclosure(), doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    found = materialize(spotted(docs, how, doc_id, text))
    told = term_spans(docs, disclosing(found, docs, how, text), how, doc_id, text)
    return found.join(told, F.col("doc_id").eqNullSafe(F.col("t_id")) & (F.col("tkey") == F.col("t_key")), "left")


def digest(docs: DataFrame, how: Disclosure = Disclosure(), doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """One row for each input row: counts by kind, a digest of the pattern spans, and all spans."""
    both = sanitised_spans(docs, how, doc_id, text)
    names = F.array(*map(F.lit, [*KINDS, "term"]))
    shown = lambda spans: F.concat_ws(",", F.transform(spans, lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["start"].cast("string"), s["end"].cast("string"))))
    bare = lambda spans: F.transform(spans, lambda s: F.struct(s["start"].alias("start"), s["kind"].alias("kind"), s["end"].alias("end")))
    every = F.sort_array(F.concat(bare(F.col("base")), F.coalesce(bare(F.col("told")), F.array().cast("array<struct<start:int,kind:int,end:int>>"))))
    count = lambda i: F.size(F.filter("base", lambda s: s["kind"] == i)).cast("long").alias(f"n_{KINDS[i]}")
    return both.select("doc_id", *map(count, range(len(KINDS))), F.sha2(shown(F.col("base")), 256).alias("base_sha256"), shown(every).alias("spans"))


def sanitise(docs: DataFrame, how: Disclosure = Disclosure()) -> DataFrame:
    """Rows of ``docs``, with their columns: entities replaced by their kind, disclosing words removed or generalised."""
    spans = sanitised_spans(docs, how).select(F.col("doc_id").alias("_p_id"), F.col("tkey").alias("_p_key"), F.col("base").alias("_p_base"), F.col("told").alias("_p_told")).filter("size(_p_base) > 0 OR _p_told IS NOT NULL").dropDuplicates(["_p_id", "_p_key"])
    keyed = docs.withColumn("_p_tkey", F.xxhash64(F.coalesce("text", F.lit(""))))
    both = keyed.join(spans, F.col("doc_id").cast("long").eqNullSafe(F.col("_p_id")) & (F.col("_p_tkey") == F.col("_p_key")), "left")
    labels = F.array(*(F.lit(f"[{k.upper()}]") for k in KINDS))
    base = F.transform("_p_base", lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), F.get(labels, s["kind"]).alias("by")))
    told = F.transform("_p_told", lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), F.when(s["ratio"] >= how.remove, F.lit("")).otherwise(F.lit("[WORD]")).alias("by")))
    every = F.sort_array(F.concat(base, F.coalesce(told, F.array().cast("array<struct<start:int,end:int,by:string>>"))))

    state = lambda pos, out: F.struct(pos.cast("int").alias("pos"), out.alias("out"))

    def block(a: Column, spans: Column) -> Column:
        """A run of spans works on its own stretch of the text, so that no span cuts from the start of a long one."""
        begin, reach = a["pos"], F.greatest(a["pos"], F.array_max(F.transform(spans, lambda s: s["end"])))

        def cut(stretch: Column) -> Column:
            def step(a: Column, s: Column) -> Column:
                kept = F.substring(stretch, a["pos"] - begin + 1, F.greatest(F.lit(0), s["start"] - a["pos"]))
                return state(F.greatest(a["pos"], s["end"]), F.concat(a["out"], kept, F.when(s["start"] >= a["pos"], s["by"]).otherwise(F.lit(""))))

            return F.aggregate(spans, state(begin, F.lit("")), step)

        own = let(F.substring(F.col("text"), begin + 1, reach - begin), cut)
        return let(own, lambda r: state(r["pos"], F.concat(a["out"], r["out"])))

    runs = F.filter(in_blocks(every), lambda x: F.size(x) > 0)
    clean = F.aggregate(runs, state(F.lit(0), F.lit("")), block, lambda a: F.concat(a["out"], F.substring(F.col("text"), a["pos"] + 1, F.length("text"))))
    out = both.withColumn("text", F.when(F.col("_p_base").isNotNull(), clean).otherwise(F.col("text")))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("_p_base").isNotNull(), F.length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")))
    return out.select(*docs.columns)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digest(spark.read.parquet(f"{sf_dir}/documents.parquet"))
