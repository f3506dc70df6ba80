"""Personal data by validated patterns and bootstrapped contextual extraction, in DataFrame functions alone.

Seed entities are e-mail addresses, network addresses, payment cards and phone numbers found by fixed patterns and checks. The words
around an entity are its lexical patterns: one or two before it, one after it, and one on either side. Entities and all other
identifier-like tokens (those with a digit or an at sign) form a graph with their patterns. In rounds, a pattern is scored by the share
of known entities of a kind among *all* the corpus's words that stand in it; patterns of high confidence and enough distinct entities
extract the unknown tokens of that kind's shape; these are known in the next round and induce patterns of their own, until no round
finds more. Every occurrence of an extracted token is a further span.

Java's matcher is kept linear: runs are possessive, start where the run starts, and separators that end a run are marked beforehand by
characters of equal length. Where a match stands follows from the pieces between the matches, summed in chunks.

Rows are told apart by a number that is written once, whatever their ids and texts. Null texts count as empty. Repeated rows are rows
like others. An empty table gives an empty table. A text of any length is read whole.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pairbundle.llm.common import doc_text, documents, staged

#: Kinds of base spans, in the order that decides between spans of equal start.
KINDS = ("email", "ip", "card", "phone")

SPAN = "array<struct<start:int,rank:int,stop:int,kind:string>>"

MATCH = "array<struct<start:int,stop:int,s:string>>"


def bound(value: Column, use) -> Column:
    """``use(value)`` with the value worked out once: a lambda's variable holds it."""
    return F.element_at(F.transform(F.array(value), use), 1)


def located(text: Column, pattern: str, chunk: int = 64) -> Column:
    """Matches from left to right as structs of start, stop (code points) and the matched string.

    Lengths are summed within chunks of matches and then over the chunks, so that growing an array costs little for any number."""
    none = F.array().cast(MATCH)

    def grown(a, x):
        begin = a["at"] + x["p"]
        one = F.struct(begin.alias("start"), (begin + x["m"]).alias("stop"), x["s"].alias("s"))
        return F.struct((begin + x["m"]).alias("at"), F.concat(a["out"], F.array(one)).alias("out"))

    def chunks(steps):
        start = F.struct(F.lit(0).alias("at"), none.alias("out"))
        last = F.floor((F.size(steps) - 1) / chunk).cast("int")
        return F.transform(F.sequence(F.lit(0), last), lambda c: F.aggregate(F.slice(steps, c * chunk + 1, F.lit(chunk)), start, grown))

    def joined(parts):
        bases = F.aggregate(parts, F.array(F.lit(0)), lambda a, c: F.concat(a, F.array(F.element_at(a, -1) + c["at"])))
        move = lambda m, base: F.struct((m["start"] + base).alias("start"), (m["stop"] + base).alias("stop"), m["s"].alias("s"))
        return F.flatten(F.zip_with(parts, F.slice(bases, F.lit(1), F.size(parts)), lambda c, base: F.transform(c["out"], lambda m: move(m, base))))

    def walked(found):
        step = lambda p, m: F.struct(F.length(p).alias("p"), F.length(m).alias("m"), m.alias("s"))
        steps = F.zip_with(F.slice(F.split(text, pattern, -1), F.lit(1), F.size(found)), found, step)
        return F.when(F.size(found) > 0, bound(steps, lambda st: bound(chunks(st), joined))).otherwise(none)

    return bound(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), walked)


def _digits(s: Column) -> Column:
    return F.regexp_replace(s, "[^0-9]", "")


def luhn(digits: Column) -> Column:
    """Whether a string of digits passes the check sum with every second digit from the right doubled."""
    n = F.length(digits)
    total = F.aggregate(
        F.transform(F.sequence(F.lit(1), n), lambda i: F.struct(F.pmod(i, F.lit(2)).alias("odd"), F.substring(digits, n - i + 1, F.lit(1)).cast("int").alias("d"))),
        F.lit(0),
        lambda s, x: s + F.when(x["odd"] == 1, x["d"]).when(x["d"] > 4, x["d"] * 2 - 9).otherwise(x["d"] * 2),
    )
    return F.pmod(total, F.lit(10)) == 0


def _finders(text: Column) -> dict[str, tuple[Column, Column, str, object]]:
    """For each kind: whether a look is worth while, the prepared text, the pattern and the check."""
    byte = lambda p: F.when(F.length(F.regexp_replace(p, "^0+", "")) <= 3, F.coalesce(F.nullif(F.regexp_replace(p, "^0+", ""), F.lit("")), F.lit("0")).cast("int") <= 255).otherwise(False)
    card = lambda m: F.when(F.length(_digits(m)).between(14, 19), luhn(_digits(m))).otherwise(False)
    return {
        "email": (F.contains(text, F.lit("@")), F.regexp_replace(text, r"\.(?![A-Za-z0-9-])", "_"), r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++\.[A-Za-z0-9.-]++", lambda m: F.lit(True)),
        "ip": (text.rlike(r"[0-9]\.[0-9]"), text, r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++", lambda m: F.forall(F.split(m, r"\."), byte)),
        "card": (text.rlike(r"[0-9][0-9 -]{12}"), F.regexp_replace(text, r"[ -](?=[ -])", "\u0001"), r"[0-9][0-9 -]*[0-9]", card),
        "phone": (F.contains(text, F.lit("+")), text, r"\+[0-9][ ().0-9-]+[0-9]", lambda m: F.length(_digits(m)).between(10, 15)),
    }


def base_spans(text: Column) -> Column:
    """All valid base spans, by start, then kind."""
    def spans(rank, kind, worth, ready, pattern, check):
        valid = F.filter(located(ready, pattern), lambda x: check(x["s"]))
        shaped = F.transform(valid, lambda x: F.struct(x["start"].alias("start"), F.lit(rank).alias("rank"), x["stop"].alias("stop"), F.lit(kind).alias("kind")))
        return F.when(worth, shaped).otherwise(F.array().cast(SPAN))

    found = [spans(rank, kind, *how) for rank, (kind, how) in enumerate(_finders(text).items())]
    return F.array_sort(F.concat(*found))


def around(words: Column) -> Column:
    """For each word: itself, the two before it and the one after it, in lower case; nulls where there is none."""
    none = F.lit(None).cast("string")

    def shifted(own, low):
        before = F.concat(F.array(none), low)
        return F.slice(F.arrays_zip(own.alias("word"), F.concat(F.array(none), before).alias("two"), before.alias("one"), F.slice(low, F.lit(2), F.size(low)).alias("after")), F.lit(1), F.size(own))

    named = "array<struct<word:string,two:string,one:string,after:string>>"
    return bound(words, lambda own: bound(F.transform(own, F.lower), lambda low: shifted(own, low))).cast(named)


def words_of(text: Column) -> Column:
    return F.filter(F.split(text, r"\s+"), lambda w: w != "")


TOKEN = "array<struct<start:int,stop:int,token:string,two:string,one:string,after:string>>"


def tokens_in_context(text: Column) -> Column:
    """Identifier-like tokens, without punctuation at their end, with the words around them, of any length. A token is a whole word, so
    the words with a digit or an at sign are the tokens in their order."""
    found = located(text, r"(?<!\S)[^\s0-9@]*+[0-9@]\S*+")
    trim = lambda s: F.regexp_replace(s, r"[^\p{L}\p{N}]+$", "")
    placed = F.filter(around(words_of(text)), lambda p: p["word"].rlike("[0-9@]"))
    one = lambda x, p: F.struct(x["start"].alias("start"), (x["start"] + F.length(trim(x["s"]))).alias("stop"), trim(x["s"]).alias("token"), p["two"].alias("two"), p["one"].alias("one"), p["after"].alias("after"))
    rows = F.filter(F.zip_with(found, placed, one), lambda t: t["token"] != "")
    return F.when(text.rlike("[0-9@]"), rows).otherwise(F.array().cast(TOKEN))


def shown(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["stop"].cast("string"))), ",")


def patterns_of(two: Column, one: Column, after: Column) -> Column:
    """The lexical patterns of a place: the words before it, after it, and around it."""
    made = [F.concat(F.lit("< "), one), F.concat(F.lit("<< "), two, F.lit(" "), one), F.concat(F.lit("> "), after), F.concat(F.lit("<> "), one, F.lit(" "), after)]
    return F.filter(F.array(*made), lambda p: p.isNotNull())


def entities(rows: DataFrame) -> DataFrame:
    """row, start, stop, entity (its string), kind (null unless a base span covers it) and the words around it: one for each base span,
    of all its tokens, and one for each token that no base span touches."""
    none = F.lit(None).cast("string")
    tokens = rows.select("row", F.inline("tokens")).withColumn("span", F.lit(None).cast("struct<stop:int,start:int,kind:string>"))
    spans = rows.select("row", F.explode("base").alias("b")).select("row", F.col("b.start").alias("start"), F.col("b.stop").alias("stop"), none.alias("token"), none.alias("two"), none.alias("one"), none.alias("after"), F.struct("b.stop", "b.start", "b.kind").alias("span"))
    upto = lambda *keys: Window.partitionBy("row").orderBy(*keys).rowsBetween(Window.unboundedPreceding, 0)
    is_token = F.col("token").isNotNull()
    before = F.max("span").over(upto("start", is_token, "stop"))
    # From the end backwards: a frame that reaches forward to the end would be worked out anew for every row.
    later = F.min(F.when(F.col("span").isNotNull(), F.struct("span.start", "span.stop", "span.kind"))).over(upto(F.desc("start"), is_token, F.desc("stop")))
    both = tokens.unionByName(spans).withColumn("before", before).withColumn("later", later).where("token IS NOT NULL")
    inside = F.when(F.col("before.stop") > F.col("start"), F.struct("before.start", "before.stop", "before.kind")).when(F.col("later.start") < F.col("stop"), F.col("later"))
    marked = both.withColumn("cover", inside)
    free = marked.where("cover IS NULL").select("row", "start", "stop", F.col("token").alias("entity"), none.alias("kind"), "two", "one", "after")
    whole = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("start", "token"))), lambda t: t["token"]), " ")
    seeds = marked.where("cover IS NOT NULL").groupBy("row", "cover").agg(whole.alias("entity"), F.min_by("two", "start").alias("two"), F.min_by("one", "start").alias("one"), F.max_by("after", "start").alias("after"))
    return seeds.select("row", "cover.start", "cover.stop", "entity", "cover.kind", "two", "one", "after").unionByName(free)


#: What a token must look like to be taken for a kind on the word of its context: a sign for an at sign between letters or digits; four
#: groups; or so many digits and no letters.
SHAPES = {
    "email": r"(?i)[a-z0-9](@|[^a-z0-9]at[^a-z0-9])[a-z0-9]",
    "ip": r"^[^\p{L}\p{N}]*[0-9]+([^\p{L}\p{N}]+[0-9]+){3}$",
    "card": r"^([^\p{L}\p{N}]*[0-9]){14,19}$",
    "phone": r"^([^\p{L}\p{N}]*[0-9]){10,15}$",
}


def shape_fits(kind: Column, token: Column) -> Column:
    fits = F.lit(False)
    for name, shape in SHAPES.items():
        fits = F.when(kind == name, token.rlike(shape)).otherwise(fits)
    return fits


def pattern_totals(texts: DataFrame, wanted: DataFrame, slots: int = 1 << 18) -> DataFrame:
    """pattern and total, the number of words of the corpus that stand in it, for the wanted patterns. The slots into which hashes of
    wanted patterns fall, at most ``slots`` numbers, are broadcast; words of other slots go before the shuffle, and the join decides."""
    slot = F.pmod(F.xxhash64("pattern"), F.lit(slots)).alias("slot")
    taken = F.broadcast(wanted.select(slot).distinct())
    places = texts.select(F.inline(around(words_of(F.col("text")))))
    each = places.select(F.explode(patterns_of(F.col("two"), F.col("one"), F.col("after"))).alias("pattern"))
    near = each.select("pattern", slot).join(taken, "slot", "left_semi")
    return near.groupBy("pattern").agg(F.count("*").alias("total")).join(wanted, "pattern", "left_semi")


def confident_patterns(edges: DataFrame, totals: DataFrame, known: DataFrame, confidence: float, support: int) -> DataFrame:
    """pattern, kind, confidence: patterns in which at least ``confidence`` of all words are known entities of one kind, ``support`` of
    them distinct."""
    hits = edges.join(known, "entity").groupBy("pattern", "kind").agg(F.sum("n").alias("hits"), F.count("*").alias("distinct"))
    share = F.col("hits") / F.greatest("total", "seen")
    return hits.where(F.col("distinct") >= support).join(totals, "pattern").withColumn("confidence", share).where(F.col("confidence") >= confidence).select("pattern", "kind", "confidence")


def bootstrap(found: DataFrame, texts: DataFrame, confidence: float = 0.7, support: int = 3) -> DataFrame:
    """entity and kind of the tokens that contexts tell, without the seeds."""
    places = found.select("entity", "kind", F.explode(F.array_distinct(patterns_of(F.col("two"), F.col("one"), F.col("after")))).alias("pattern"))
    edges = staged(places.groupBy("pattern", "entity").agg(F.count("*").alias("n"), F.max("kind").alias("seed")), "pattern-graph", narrow=True)
    wide = edges.groupBy("pattern").agg(F.count("*").alias("entities"), F.sum("n").alias("seen"), F.count("seed").alias("seeds")).where(F.col("entities") >= support)
    wide = staged(wide, "patterns", narrow=True)
    totals = staged(pattern_totals(texts, wide.select("pattern")).join(wide, "pattern").select("pattern", "total", "seen"), "pattern-totals", narrow=True)
    near = edges.drop("seed").join(totals.select("pattern"), "pattern", "left_semi")
    seeds = found.where("kind IS NOT NULL").groupBy("entity").agg(F.max("kind").alias("kind"))
    known = staged(seeds, "known", narrow=True)
    told = known.limit(0)
    while True:
        good = confident_patterns(near, totals, known, confidence, support)
        told_by = near.join(good, "pattern").join(known.select("entity"), "entity", "left_anti").where(shape_fits(F.col("kind"), F.col("entity")))
        more = staged(told_by.groupBy("entity").agg(F.max_by("kind", F.struct("confidence", "kind")).alias("kind")), "told", narrow=True)
        if more.isEmpty():
            return told
        told, known = told.unionByName(more), known.unionByName(more)


def find_personal_data(docs: DataFrame, **options) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans and n_spans of every row."""
    texts = doc_text(docs)
    made = texts.select("doc_id", base_spans(F.col("text")).alias("base"), tokens_in_context(F.col("text")).alias("tokens"))
    rows = staged(made.withColumn("row", F.monotonically_increasing_id()), "spans")
    found = staged(entities(rows), "entities", narrow=True)
    told = bootstrap(found, texts, **options)
    rank = F.coalesce(*[F.when(F.col("kind") == k, F.lit(i)) for i, k in enumerate(KINDS)])
    more = found.where("kind IS NULL").drop("kind").join(told, "entity")
    extra = more.groupBy("row").agg(F.collect_list(F.struct("start", rank.alias("rank"), "stop", "kind")).alias("extra"))
    out = rows.select("doc_id", "row", "base").join(extra, "row", "left")
    count = lambda kind: F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    every = F.array_sort(F.concat("base", F.coalesce("extra", F.array().cast(SPAN))))
    digest = F.sha2(shown(F.col("base")).cast("binary"), 256)
    return out.select("doc_id", *map(count, KINDS), digest.alias("base_sha256"), shown(every).alias("spans"), F.size(every).cast("long").alias("n_spans"))


def op9_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_personal_data(documents(spark, sf_dir))
