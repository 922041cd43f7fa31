"""Benchmark decontamination by template canonicalisation, in DataFrame functions only.

Numbers, quantities with units, units after numbers and names (capitalised words inside a sentence) become typed
placeholders, case and ASCII punctuation go, and the number of words stays the same, but that
a number and its unit become one in either spelling (it counts as the words that the item has). Capitalised words at sentence starts and after quotes,
brackets and other marks may be names or not: texts are compared in two forms, with those words kept and with them as names. A benchmark item is indexed by every window of
``WINDOW`` canonical words. Each of its windows names its anchor, the run of ``ANCHOR`` words with the most letters outside placeholders; every place of a document is
looked up among the anchors, and where one stands, the whole window around it is compared, so a leaked run of WINDOW words can't be missed.
Shorter items are one window: they match as a whole only, and unless all their words are the same, at least half of them must be no slots.
Each hit aligns the item with the document; the aligned words are compared, and slots are checked: the slot values of the item and
of the document must map one to one. That finds questions asked again with other numbers and names. Windows of the index are
broadcast if their counted number is at most ``BROADCAST_ROWS`` and the items' texts take at most ``BROADCAST_BYTES``, else joined by a shuffle on the hash.

Where words were put in or left out, an item's parts lie at several shifts; the parts found in one stretch of the document are added up.

A row is a leak: coverage (share of the item's words that the document has in place) of at least ``min_coverage``, with consistent slots, in a form of which a window hit.
Items without words match nothing. Nulls: null texts, ids or items match nothing, except
that a null doc_id is reported as null. Repeated documents with one id give one row for each item. An empty table on either side gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import durable, table

WINDOW = 8
ANCHOR = 3
BROADCAST_ROWS, BROADCAST_BYTES = 1_000_000, 1 << 24
UNITS = "km|cm|mm|m|mi|ft|in|kg|g|mg|lb|oz|l|ml|s|ms|min|h|hours?|minutes?|seconds?|days?|weeks?|months?|years?|meters?|metres?|miles?|feet|inches|grams?|kilograms?|liters?|litres?|percent|dollars?|euros?|cents?|usd|eur"
NUMBER = r"(?<![^ ])[^\p{L}\p{N} ]*\p{N}[^\p{L} ]*(?![^ ])"
QUANTITY = rf"(?i)(?<![^ ])[^\p{{L}}\p{{N}} ]*\p{{N}}[\p{{N}}.,]*\x1f?(?:{UNITS}|%)[^\p{{L}}\p{{N}} ]*(?![^ ])"
UNIT = rf"(?i)(?<=<num> )(?:{UNITS})(?![\p{{L}}\p{{N}}])"
NAME = r"(?<=[\p{Ll}\p{N},;] )\p{Lu}\p{L}*"
START, JOINT = "\x02", "\x1f"
MEASURE = rf"(?i)(?<![^ ])([^\p{{L}}\p{{N}} ]*\p{{N}}(?:[\p{{N}}.,]*\p{{N}})?) (?=(?:{UNITS}|%)(?![\p{{L}}\p{{N}}]))"
OPENING = r"(?<![^ ])(?=[^\p{L}\p{N} ]*\p{Lu})([^\p{L}\p{N} ]*)"
ANY_NAME = rf"(?<![^ ])(?:{START}|[^ <]*+<name>)[^ ]*"
MARKS = r"[!-/:;=?@\[-`{-~]+"
FORMS = ("plain", "named")
SLOTS = ("<num>", "<qty>", "<unit>", "<name>")


def spaced(text: Column) -> Column:
    """Words with single spaces between; the marks that canonical texts use count as white space."""
    plain = F.translate(text, f"\t\n\x0b\x0c\r{START}{JOINT}", " " * 7)
    return F.trim(F.when(F.contains(plain, F.lit("  ")), F.regexp_replace(plain, " {2,}", " ")).otherwise(plain))


def marked(clean: Column) -> Column:
    """Canonical text of a text with single spaces and joined measures; it has as many words. Other capitalised words are kept behind a START."""
    named = F.when(clean.rlike(r"[\p{Ll}\p{N},;] \p{Lu}"), F.regexp_replace(clean, NAME, "<name>")).otherwise(clean)
    named = F.regexp_replace(named, OPENING, f"{START}$1")
    plain = F.regexp_replace(F.lower(named), MARKS, "")
    numbered = F.regexp_replace(F.regexp_replace(F.regexp_replace(named, QUANTITY, "<qty>"), NUMBER, "<num>"), UNIT, "<unit>")
    return F.when(clean.rlike(r"\p{N}"), F.regexp_replace(F.lower(numbered), MARKS, "")).otherwise(plain)


def _words(df: DataFrame, text: str) -> DataFrame:
    """raw words (a number and its unit are one, with a JOINT inside) and their two canonical forms: `plain` keeps capitalised words at sentence starts and after marks, `named` takes them for names."""
    text = df.withColumn("clean", spaced(F.col(text))).withColumn("clean", F.regexp_replace("clean", MEASURE, f"$1{JOINT}")).withColumn("m", marked(F.col("clean")))
    return text.select("*", F.split("clean", " ").alias("raw"), F.split(F.translate("m", START, ""), " ").alias("plain"), F.split(F.regexp_replace("m", ANY_NAME, "<name>"), " ").alias("named"), *([] if "key" in df.columns else [F.xxhash64("clean").alias("key")])).drop("m", "clean", "t")


def _hash(form: str, words: list[Column]) -> Column:
    return F.xxhash64(F.lit(form), *words)


def _windows(words: int) -> Column:
    """(place, form, hash, anchor) of all windows of so many words, in both canonical forms."""
    last = F.size("raw") - words
    at = F.when(last >= 0, F.sequence(F.lit(0), last)).otherwise(F.array().cast("array<int>"))
    run = min(words, ANCHOR)
    letters = lambda w: F.when(w.isin(*SLOTS), 0).otherwise(F.char_length(w))

    def anchor(f: str, i: Column) -> Column:
        parts = [[F.get(f, i + (o + k)) for k in range(run)] for o in range(words - run + 1)]
        return F.array_max(F.array(*[F.struct(sum(map(letters, own[1:]), letters(own[0])).alias("letters"), _hash(f, own).alias("run"), F.lit(o).alias("offset")) for o, own in enumerate(parts)]))

    of = lambda f: F.transform(at, lambda i: F.struct(i.alias("place"), F.lit(FORMS.index(f)).alias("form"), _hash(f, [F.get(f, i + k) for k in range(words)]).alias("hash"), anchor(f, i).alias("anchor")))
    return F.concat(*map(of, FORMS))


def _found(texts: DataFrame, index: DataFrame, lengths: list[int], near) -> DataFrame:
    """Texts in which windows of the index stand: doc_id, key, words in their forms, and `found`: doc_place, form and hash of each window.

    Rows that meet the anchors carry a hash of up to ANCHOR words and no text; only texts with an anchor are read again."""
    at = F.explode(F.when(F.size("raw") > 0, F.sequence(F.lit(0), F.greatest(*[F.size(f) for f in FORMS]) - 1)))  # places alone: words are hashed where they stand
    places = _words(texts, "t").select("key", *FORMS, at.alias("at"))
    runs = [(i, _hash(f, [F.get(f, F.col("at") + k) for k in range(m)])) for i, f in enumerate(FORMS) for m in sorted({min(n, ANCHOR) for n in lengths})]
    probes = places.select("key", "at", F.stack(F.lit(len(runs)), *[x for i, h in runs for x in (F.lit(i), h)]).alias("form", "run"))
    anchors = index.select("form", F.col("anchor.run").alias("run"), F.col("anchor.offset").alias("offset"), "hash", F.least("length", F.lit(WINDOW)).alias("words")).distinct()
    met = probes.join(near(anchors), ["form", "run"]).select("key", F.struct((F.col("at") - F.col("offset")).alias("doc_place"), "form", "words", "hash").alias("c")).where("c.doc_place >= 0")
    met = met.groupBy("key").agg(F.collect_set("c").alias("met"))
    again = durable(_words(texts.join(met, "key"), "t").select("doc_id", "key", "raw", *FORMS, "met"), "anchored")  # else the filter makes words anew for each window
    whole = lambda c: F.coalesce(*[F.when((c.form == i) & (c.words == n), _hash(f, [F.get(f, c.doc_place + k) for k in range(n)]) == c.hash) for i, f in enumerate(FORMS) for n in lengths], F.lit(False))
    again = again.withColumn("found", F.filter("met", lambda c: (c.doc_place + c.words <= F.size("raw")) & whole(c))).drop("met")
    return durable(again.dropDuplicates(["key"]), "hits").where(F.size("found") > 0)


def _weight(word: Column) -> Column:
    return F.when(F.contains(word, F.lit(JOINT)), 2).otherwise(1)


def _one_to_one(slots: Column) -> Column:
    size = lambda a: F.size(F.array_distinct(a))
    return (size(slots) == size(F.transform(slots, lambda s: s.i))) & (size(slots) == size(F.transform(slots, lambda s: s.d)))


def _with_slots(rows: DataFrame) -> DataFrame:
    """slots (i, d) of pairs. A word that several shifts align with different words, as one name with one of two words, has all of these as its value."""
    rows = rows.withColumn("slot", F.sort_array(F.array_distinct(F.transform(F.filter("pairs", lambda p: p.slot), lambda p: F.struct(p.at.alias("at"), p.to.alias("to"), p.i.alias("i"), p.d.alias("d"))))))

    plain = F.transform("slot", lambda x: F.struct(x.i.alias("i"), x.d.alias("d")))

    def word(at: Column) -> Column:
        own = F.filter("slot", lambda x: x.at == at)
        return F.struct(own[0].i.alias("i"), F.transform(own, lambda x: x.to).alias("to"), F.array_join(F.transform(own, lambda x: x.d), " ").alias("d"))

    rows = rows.withColumn("word", F.transform(F.array_distinct(F.transform("slot", lambda x: x.at)), word))

    def value(to: Column) -> Column:
        own = F.filter("word", lambda x: x.to == to)
        return F.struct(F.array_join(F.transform(own, lambda x: x.i), " ").alias("i"), own[0].d.alias("d"))

    return rows.withColumn("slots", F.when(F.col("parts") == 1, plain).otherwise(F.transform(F.array_distinct(F.transform("word", lambda x: x.to)), value))).drop("slot", "word")


def _combined(one: DataFrame) -> DataFrame:
    """Alignments of a document and item at several shifts, in stretches of the document without a gap of more than the item's length: all of a stretch, and
    those of it that keep the item's order, where words between the windows count for the shift before and after them."""
    texts = ["doc_id", "key", "item_id", "item_key", "form"]
    by_place = Window.partitionBy(*texts).orderBy(F.col("begin") + F.col("shift"), "begin")
    before = F.max(F.col("end") + F.col("shift")).over(by_place.rowsBetween(Window.unboundedPreceding, -1))
    gap = F.coalesce(F.col("begin") + F.col("shift") - before > F.col("length"), F.lit(False))
    back = F.coalesce(F.col("begin") < F.lag("begin").over(by_place), F.lit(False))
    rows = one.where(F.col("length") >= WINDOW).withColumn("gap", gap).withColumn("back", F.col("gap") | back)
    rows = rows.withColumn("loose", F.sum(F.col("gap").cast("int")).over(by_place)).withColumn("strict", F.sum(F.col("back").cast("int")).over(by_place))
    in_chain = Window.partitionBy(*texts, "strict").orderBy(F.col("begin") + F.col("shift"), "begin")
    rows = rows.withColumn("from", F.least("begin", F.coalesce(F.lag("end").over(in_chain), F.lit(0)))).withColumn("to", F.greatest("end", F.coalesce(F.lead("begin").over(in_chain), F.col("length"))))

    def chains(name: str, first: str, last: str) -> DataFrame:
        own = F.filter("pairs", lambda p: (p.at >= F.col(first)) & (p.at < F.col(last)))
        out = rows.groupBy(*texts, name).agg(F.first("n_words").alias("n_words"), F.first("length").alias("length"), F.count("*").cast("int").alias("parts"), F.flatten(F.collect_list(own)).alias("pairs"))
        return out.where(F.col("parts") > 1).select("doc_id", "item_id", "n_words", "length", "form", "parts", "pairs")

    return chains("loose", "begin", "end").unionByName(chains("strict", "from", "to"))


def find_leaks(docs: DataFrame, items: DataFrame, min_coverage: float = 0.5, doc_id: str = "doc_id", text: str = "text", item_id: str = "item_id", item_text: str = "text") -> DataFrame:
    """doc_id, item_id, n_words, n_matched, coverage, n_slots, exact: one row for each document and item it leaks."""
    bench = _words(items.select(F.col(item_id).alias("item_id"), F.col(item_text).alias("t")).where("t is not null"), "t").where("raw <> array('')")
    bench = bench.withColumn("length", F.size("raw")).withColumn("n_words", F.aggregate(F.transform("raw", _weight), F.lit(0), lambda a, x: a + x)).withColumn("item_key", F.xxhash64("item_id", "key")).drop("key").dropDuplicates(["item_key"])
    lengths = sorted(r[0] for r in bench.select(F.least("length", F.lit(WINDOW))).distinct().collect()) or [WINDOW]  # WINDOW rows at most
    sizes = F.inline(F.concat(*[F.when(F.least("length", F.lit(WINDOW)) == k, _windows(k)).otherwise(F.slice(_windows(k), 1, 0)) for k in lengths]))
    index = bench.select("item_id", "item_key", "n_words", "length", sizes)
    size = bench.agg(F.coalesce(2 * F.sum("length"), F.lit(0)).alias("rows"), F.coalesce(F.sum(F.octet_length(F.array_join("raw", " "))), F.lit(0)).alias("bytes")).first()
    small = size.rows <= BROADCAST_ROWS and size.bytes <= BROADCAST_BYTES
    near = F.broadcast if small else lambda df: df
    texts = docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("t")).where("t is not null").withColumn("key", F.xxhash64("doc_id", "t"))
    hits = _found(texts, index, lengths, near)
    hit = hits.select("key", F.inline("found").alias("doc_place", "form", "words", "hash")).join(near(index.drop("anchor")), ["form", "hash"])
    hit = hit.withColumn("shift", F.col("doc_place") - F.col("place"))
    hit = hit.groupBy("key", "item_id", "item_key", "n_words", "length", "form", "shift").agg(F.min("place").alias("place"), F.max("place").alias("last"))
    hit = hits.drop("found").join(hit, "key")
    skip = F.greatest(-F.col("shift"), F.lit(0))  # words of the item that lie before the document's begin
    part = lambda a: F.slice(a, F.greatest(F.col("shift"), F.lit(0)) + 1, F.greatest(F.col("length") - skip, F.lit(0)))
    of_form = lambda prefix: F.when(F.col("form") == 0, F.col(f"{prefix}{FORMS[0]}")).otherwise(F.col(f"{prefix}{FORMS[1]}"))
    aligned = hit.select("doc_id", "key", "item_id", "item_key", "n_words", "length", "form", "shift", "place", "last", part(F.col("raw")).alias("dr"), part(of_form("")).alias("dc"))
    once = aligned.groupBy("doc_id", "key", "item_id", "item_key", "form", "shift").agg(F.min("place").alias("begin"), (F.max("last") + F.least(F.first("length"), F.lit(WINDOW))).alias("end"), *[F.first(c).alias(c) for c in ("n_words", "length", "dr", "dc")])
    once = once.join(near(bench.select("item_key", *[F.col(c).alias(f"item_{c}") for c in ("raw", *FORMS)])), "item_key")
    item = lambda a: F.slice(a, skip + 1, F.col("length"))
    once = once.withColumn("ir", item(F.col("item_raw"))).withColumn("ic", item(of_form("item_")))
    bare = lambda c: F.regexp_replace(F.lower(F.translate(c, JOINT, "")), r"(?<=^)[!-/:;=?@\[-`{-~]+|[!-/:;=?@\[-`{-~]+$", "")
    n = F.least(F.size("ir"), F.size("dr"))
    at = lambda c, k: F.element_at(c, k)
    pair = lambda k: F.struct((skip + k - 1).alias("at"), (skip + k - 1 + F.col("shift")).alias("to"), _weight(at("ir", k)).alias("weight"), (at("ic", k) == at("dc", k)).alias("same"), ((at("ic", k) == at("dc", k)) & at("dc", k).isin(*SLOTS)).alias("slot"), bare(at("ir", k)).alias("i"), bare(at("dr", k)).alias("d"))
    pairs = F.when(n > 0, F.transform(F.sequence(F.lit(1), n), pair)).otherwise(F.array())
    one = durable(once.withColumn("pairs", pairs).drop("ir", "ic", "dr", "dc", *[f"item_{c}" for c in ("raw", *FORMS)]), "aligned")  # else each lambda aligns anew
    one = one.withColumn("pairs", F.filter("pairs", lambda p: p.same | (p.i == p.d)))
    scored = one.select("doc_id", "item_id", "n_words", "length", "form", F.lit(1).alias("parts"), "pairs").unionByName(_combined(one))
    scored = durable(_with_slots(scored), "slots")
    count = lambda pairs: F.aggregate(F.array_distinct(F.transform(pairs, lambda p: F.struct(p.at.alias("at"), p.weight.alias("weight")))), F.lit(0), lambda a, p: a + p.weight)
    scored = scored.withColumn("n_slots", F.size("slots")).withColumn("n_matched", count(F.col("pairs")))
    scored = scored.withColumn("exact", (F.col("parts") == 1) & (count(F.filter("pairs", lambda p: p.i == p.d)) == F.col("n_words")))
    enough = (F.col("length") >= WINDOW) | ((F.col("n_matched") == F.col("n_words")) & (F.col("exact") | (2 * F.col("n_slots") <= F.col("length"))))
    kept = scored.where(_one_to_one(F.col("slots")) & enough & (F.col("n_matched") >= F.lit(min_coverage) * F.col("n_words")))
    best = kept.groupBy("doc_id", "item_id").agg(F.max(F.struct("n_matched", "exact", (-F.col("form")).alias("way"), "n_slots", "n_words")).alias("b"))
    return best.select("doc_id", "item_id", F.col("b.n_words").cast("long").alias("n_words"), F.col("b.n_matched").cast("long").alias("n_matched"), (F.col("b.n_matched") / F.col("b.n_words")).alias("coverage"), F.col("b.n_slots").cast("long").alias("n_slots"), F.col("b.exact").alias("exact"))


def op4(spark, sf_dir: str) -> DataFrame:
    return find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
