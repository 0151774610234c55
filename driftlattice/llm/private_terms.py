"""Personal data: pattern spans, and terms that reveal protected entities (native: DataFrame functions only).

Protected entities are the e-mail addresses, IP addresses, card and phone numbers that patterns
find. The information-theoretic part asks which words give them away: within NEAR words of an
entity, a term t discloses entity e by

    pmi(t, e) / ic(e) = log2(n(t, e) * N / (n(t) * n(e))) / log2(N / n(e)),

the share of e's information content that seeing t reveals (1: t occurs beside e only). n(t, e)
and n(e) count distinct contexts, so copies of a document are no evidence; n(t) counts all places
of t in the whole corpus, glued into longer tokens or not, and N the places of all words. Pairs seen in fewer than SUPPORT contexts say nothing. Terms at REMOVE or more for some
entity are removed, from GENERALISE on replaced by their kind of word: at every place of every text
where they stand as words, beside an entity or not.

Spans are found without user code: matches are wrapped in a control character that no pattern
knows, the text is split there, and running lengths give code point positions, in blocks of BLOCK
pieces, so that texts with very many matches take no quadratic time. Patterns are written so that no
start is tried twice within a run of characters, which keeps very long words linear.

Defined cases: null and empty texts have no spans; kinds may overlap and are listed each; equal
starts keep the kinds' order (email, ip, card, phone, term); repeated rows and ids give a row each;
null ids are kept; an empty table gives an empty result; other columns are kept by stage() whatever
their names, and with_spans() refuses to name its two columns like one of the table.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from driftlattice.llm.shared import field, fresh, let, written

KINDS = ("email", "ip", "card", "phone", "term")
NEAR = 4
REACH = 80
SUPPORT = 2
GENERALISE, REMOVE = 0.75, 0.9
#: Terms, and spans of terms, that may be broadcast; their number is checked, and beyond it joins shuffle.
BROADCAST_TERMS, BROADCAST_SPANS = 200_000, 1_000_000
#: Pieces of a text whose places are summed up at once (even: matches are every other piece).
BLOCK = 64

_LOCAL = "A-Za-z0-9._%+-"
#: Pattern, cheap test that must hold for any match. The fixed grammar of the four kinds.
PATTERNS = {
    "email": (rf"(?:(?<![{_LOCAL}])|\G)[{_LOCAL}]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++", r"@[A-Za-z0-9-]"),
    "ip": (r"(?:(?<![0-9])|\G)[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++", r"[0-9]\.[0-9]++\.[0-9]++\.[0-9]"),
    "card": (r"(?<![0-9])(?<![0-9][\x20-])[0-9](?:[\x20-]?[0-9]){11,18}(?![\x20-]?[0-9])", r"[0-9](?:[\x20-]?[0-9]){11}"),
    "phone": (r"\+[0-9][\x20().0-9-]+[0-9]", r"\+[0-9]"),
}
TERM = r"(?<![\p{L}\p{N}@._%+-])\p{L}{3,40}+(?![\p{L}\p{N}@_%+])"


_FOUND = "array<struct<start:int,end:int,value:string>>"
_SPANS = "array<struct<start:int,rank:int,kind:string,end:int,value:string>>"


def located(text: Column, pattern: str) -> Column:
    """array<struct<start, end, value>> of all matches, leftmost and non-overlapping, in code points."""

    def places(pieces, at):
        def step(s, piece):
            end = s["at"] + F.length(piece)
            return F.struct(
                end.alias("at"), (s["n"] + 1).alias("n"),
                F.when(s["n"] % 2 == 1, F.concat(s["found"], F.array(F.struct(s["at"].alias("start"), end.alias("end"), piece.alias("value"))))).otherwise(s["found"]).alias("found"),
            )

        return F.aggregate(pieces, F.struct(at.cast("int").alias("at"), F.lit(0).alias("n"), F.array().cast(_FOUND).alias("found")), step, lambda s: s["found"])

    def in_blocks(pieces):
        blocks = F.transform(F.sequence(F.lit(0), F.floor((F.size(pieces) - 1) / BLOCK).cast("int")), lambda i: F.slice(pieces, i * BLOCK + 1, BLOCK))
        width = lambda block: F.aggregate(block, F.lit(0), lambda n, piece: n + F.length(piece))
        grow = lambda s, n: F.struct((s["at"] + n).alias("at"), F.concat(s["starts"], F.array(s["at"])).alias("starts"))
        starts = lambda bs: F.aggregate(F.transform(bs, width), F.struct(F.lit(0).alias("at"), F.array().cast("array<int>").alias("starts")), grow, lambda s: s["starts"])
        return let(blocks, lambda bs: F.flatten(F.zip_with(bs, starts(bs), places)))

    split = F.split(F.regexp_replace(F.translate(text, "\u0001", "\u0002"), pattern, "\u0001$0\u0001"), "\u0001")
    return let(split, lambda pieces: F.when(F.size(pieces) <= 2 * BLOCK, places(pieces, F.lit(0))).otherwise(in_blocks(pieces)))


def luhn(digits: Column) -> Column:
    total = F.aggregate(
        F.sequence(F.lit(1), F.length(digits)), F.lit(0),
        lambda s, i: s + F.element_at(
            F.when((F.length(digits) - i) % 2 == 1, F.array(*[F.lit(x) for x in (0, 2, 4, 6, 8, 1, 3, 5, 7, 9)])).otherwise(F.array(*[F.lit(x) for x in range(10)])),
            F.substring(digits, i, F.lit(1)).cast("int") + 1,
        ),
    )
    return total % 10 == 0


def valid(kind: str, value: Column) -> Column:
    digits = F.regexp_replace(value, "[^0-9]", "")
    if kind == "ip":
        return F.forall(F.split(value, r"\."), lambda part: part.try_cast("double") <= 255)
    if kind == "card":
        return F.length(digits).between(12, 19) & luhn(digits)
    if kind == "phone":
        return F.length(digits).between(9, 15)
    return F.lit(True)


def base_spans(text: Column) -> Column:
    """array<struct<start, rank, kind, end, value>> of the four pattern kinds, by start, then kind."""
    none = F.array().cast(_SPANS)

    def of_kind(rank: int, kind: str, pattern: str, test: str) -> Column:
        kept = F.filter(located(text, pattern), lambda m: valid(kind, m["value"]))
        made = F.transform(kept, lambda m: F.struct(m["start"].alias("start"), F.lit(rank).alias("rank"), F.lit(kind).alias("kind"), m["end"].alias("end"), m["value"].alias("value")))
        return F.when(F.rlike(text, F.lit(test)), made).otherwise(none)

    each = [of_kind(rank, kind, *both) for rank, (kind, both) in enumerate(PATTERNS.items())]
    return F.array_sort(F.concat(*each))


def joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def entity_contexts(docs: DataFrame) -> DataFrame:
    """docs(text) -> distinct (entity, context, term): words near entities, and a digest of all words there."""
    text = F.col("text")

    def beside(s):
        left_at = F.greatest(F.lit(0), s["start"] - REACH)
        left, right = F.substring(text, left_at + 1, s["start"] - left_at), F.substring(text, s["end"] + 1, F.lit(REACH))
        # a word that the reach cuts in two is not a word
        before = F.filter(located(left, TERM), lambda w: (w["start"] > 0) | (left_at == 0))
        after = F.filter(located(right, TERM), lambda w: w["end"] < REACH)
        words = F.concat(F.slice(F.reverse(before), 1, NEAR), F.slice(after, 1, NEAR))
        return F.struct(F.lower(s["value"]).alias("entity"), F.transform(words, lambda w: F.lower(w["value"])).alias("words"))

    any_kind = F.lit(False)
    for _, test in PATTERNS.values():
        any_kind = any_kind | F.rlike(text, F.lit(test))
    # explode_outer: a plain explode would make the optimizer test the array first, and so find all spans twice
    near = docs.select(F.col("text").cast("string").alias("text")).where(any_kind).select(F.explode_outer(F.transform(base_spans(text), beside)).alias("x")).where("x IS NOT NULL")
    return near.select("x.entity", F.xxhash64(F.array_join("x.words", " ")).alias("context"), F.explode("x.words").alias("term")).distinct()


def words_of(text: Column) -> Column:
    """The words of a text that could be terms, one row each (one null row where there are none)."""
    return F.explode_outer(F.regexp_extract_all(text, F.lit(TERM), F.lit(0)))


def few(df: DataFrame, most: int) -> bool:
    """Whether a table may be broadcast: its rows are counted, never assumed."""
    return df.limit(most + 1).count() <= most


def corpus_counts(docs: DataFrame, terms: DataFrame) -> tuple[DataFrame, int]:
    """(term, n) of the given terms over all words of all texts, and the number of words."""
    names = terms.select("term").distinct()
    words = docs.select(words_of(F.col("text").cast("string")).alias("word")).where("word IS NOT NULL").select(F.lower("word").alias("word"))
    if few(names, BROADCAST_TERMS):  # all other words are counted together, so the counts are few as well
        counts = words.join(F.broadcast(names), words.word == names.term, "left").groupBy("term").agg(F.count(F.lit(1)).alias("n")).coalesce(8)
    else:
        counts = words.groupBy(F.col("word").alias("term")).agg(F.count(F.lit(1)).alias("n"))
    counts = written(counts)
    return counts.join(names, "term"), int(counts.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0])


def revealing_terms(docs: DataFrame, contexts: DataFrame, support: int = SUPPORT, floor: float = GENERALISE, remove: float = REMOVE) -> DataFrame:
    """(entity, term, disclosure, action) of the terms that disclose an entity."""
    entity = contexts.select("entity", "context").distinct().groupBy("entity").agg(F.count(F.lit(1)).alias("n_e"))
    both = written(contexts.groupBy("entity", "term").agg(F.count(F.lit(1)).alias("n_te")).where(F.col("n_te") >= support))
    counts, total = corpus_counts(docs, both)
    everything = float(max(total, 2))
    # contexts are cut out of their texts, where a word may look whole that is not; a term counts its contexts at least
    n_t = F.greatest(F.coalesce("n", F.lit(0)), "n_te")
    pmi = F.log2(F.col("n_te") * everything / (n_t * F.col("n_e")))
    share = pmi / F.greatest(F.log2(everything / F.col("n_e")), F.lit(1e-9))
    scored = both.join(entity, "entity").join(counts, "term", "left").withColumn("disclosure", share)
    return scored.where(F.col("disclosure") >= floor).select("entity", "term", "disclosure", F.when(F.col("disclosure") >= remove, "remove").otherwise("generalise").alias("action"))


def term_spans(docs: DataFrame, revealing: DataFrame) -> DataFrame:
    """docs(text), (term, action) -> (text_key, terms array of spans): every place of a revealing term, per distinct text."""
    flagged = written(revealing.groupBy("term").agg(F.max("action").alias("action")))  # 'remove' is above 'generalise'
    if flagged.isEmpty():
        return flagged.select(F.col("term").alias("text_key"), F.array().cast(_SPANS).alias("terms"))
    flagged = F.broadcast(flagged) if few(flagged, BROADCAST_TERMS) else flagged
    texts = docs.select(F.sha2(F.col("text").cast("string"), 256).alias("text_key"), F.col("text").cast("string").alias("text"))
    # texts that hold a flagged word at all, then the words' places in these texts only
    held = texts.select("text_key", words_of(F.col("text")).alias("word")).where("word IS NOT NULL").select("text_key", F.lower("word").alias("term"))
    held = written(held.join(flagged, "term", "left_semi").select("text_key").distinct())
    placed = texts.join(F.broadcast(held) if few(held, BROADCAST_TERMS) else held, "text_key", "left_semi").select("text_key", F.explode_outer(located(F.col("text"), TERM)).alias("w")).where("w IS NOT NULL")
    hit = placed.withColumn("term", F.lower("w.value")).join(flagged, "term")
    span = F.struct(F.col("w.start").alias("start"), F.lit(4).alias("rank"), F.lit("term").alias("kind"), F.col("w.end").alias("end"), F.concat_ws(":", "action", "w.value").alias("value"))
    return hit.groupBy("text_key").agg(F.array_sort(F.collect_set(span)).alias("terms"))


def with_spans(docs: DataFrame, base: str = "base", terms: str = "terms") -> DataFrame:
    """docs(text, ...) -> the same with `base` (array of pattern spans) and `terms` (array of revealing terms), under names that the table does not have."""
    taken = [c for c in (base, terms) if fresh(docs.columns, c) != c]
    if taken:
        raise ValueError(f"the table has a column {taken[0]}; name the new columns otherwise")
    key = fresh([*docs.columns, base, terms], "text_key")
    text, none = F.col("text").cast("string"), F.array().cast(_SPANS)
    marked = docs.withColumn(base, F.coalesce(base_spans(text), none))
    found = written(term_spans(docs, revealing_terms(docs, written(entity_contexts(docs)))))
    size = found.agg(F.coalesce(F.sum(F.size("terms")), F.lit(0))).first()[0]
    if not size:  # the usual case: no join at all
        return marked.withColumn(terms, none)
    # equal texts have equal spans, so the text's digest, not a row id, leads back to the rows
    found = found.select(F.col("text_key").alias(key), F.col("terms").alias(terms))
    out = marked.withColumn(key, F.sha2(text, 256)).join(F.broadcast(found) if size <= BROADCAST_SPANS else found, key, "left")
    return out.withColumn(terms, F.coalesce(field(terms), none)).drop(key)


def all_spans(base: Column, terms: Column) -> Column:
    return F.array_sort(F.concat(base, terms))


def sanitised(text: Column, spans: Column) -> Column:
    """The text with pattern spans replaced by their kind, terms removed or generalised; overlaps go with the first span."""
    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<since:int,start:int,mask:string>>").alias("cuts"))

    def step(s, x):
        mask = F.when(x["kind"] != "term", F.concat(F.lit("["), F.upper(x["kind"]), F.lit("]"))).when(F.startswith(x["value"], F.lit("remove:")), F.lit("")).otherwise(F.when(F.rlike(x["value"], F.lit(r":\p{Lu}")), F.lit("[NAME]")).otherwise(F.lit("[WORD]")))
        cut = F.struct(s["at"].alias("since"), x["start"].alias("start"), mask.alias("mask"))
        return F.when(x["start"] < s["at"], s).otherwise(F.struct(x["end"].alias("at"), F.concat(s["cuts"], F.array(cut)).alias("cuts")))

    def joined_up(s):
        parts = F.transform(s["cuts"], lambda c: F.concat(F.substring(text, c["since"] + 1, c["start"] - c["since"]), c["mask"]))
        return F.concat(F.array_join(parts, ""), F.substring(text, s["at"] + 1, F.length(text)))

    return let(F.aggregate(spans, start, step), joined_up)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = with_spans(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
    n = lambda kind: F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    return docs.select("doc_id", n("email"), n("ip"), n("card"), n("phone"), F.sha2(joined(F.col("base")), 256).alias("base_sha256"), joined(all_spans(F.col("base"), F.col("terms"))).alias("spans"), F.size("terms").cast("long").alias("n_terms"))


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: texts with their personal data masked; n_chars follows the new text where it was set."""
    base = fresh(docs.columns, "base")
    terms = fresh([*docs.columns, base], "terms")
    marked = with_spans(docs, base, terms)
    spans = all_spans(F.col(base), F.col(terms))
    text = F.when(F.size(spans) > 0, sanitised(F.col("text"), spans)).otherwise(F.col("text"))
    out = marked.withColumn("text", text)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("n_chars").isNull() | (F.size(spans) == 0), F.col("n_chars")).otherwise(F.length("text").cast("long")))
    return out.select(*[field(c) for c in docs.columns])
