"""Benchmark decontamination by canonical templates, in SQL functions only.

Numbers, units and names become typed placeholders (a marker character; the value stays beside it in a second, aligned
word list), so a question whose values were changed keeps its template. A capitalised word that may merely start a sentence (at the start of a text, sentence or line, after a quote,
bracket or digit) is read in both ways, as a plain word and as a name, in documents and items.

First, all documents are reduced to hashes of their windows, with every capitalised word read as a name, and those that hold any
window of an item (in one of the item's readings) are noticed; the benchmark side is broadcast only if its counted windows stay under a bound,
else both sides shuffle by hash. Windows with their values are made of the noticed texts alone, once for equal texts, and
joined with the items' by hash. For each
document and item the slots are compared: every value of the item must always map to the same value of the document.
This is asked of each placement by itself (the windows found at one offset between item and document), of the windows whose
values equal the item's, and of the first places; placements that agree with each other are joined. A pair counts as a
leak if one of them, with the windows without values, holds at least `coverage` of the item's windows, or `run` of them.

Edge cases: null or empty texts have no windows; an item shorter than a window is matched as a whole by windows of its own
length; items without words are skipped; rows without an id are reported under null; rows that repeat an id and item are reported once; extra columns are ignored; an empty
table on either side gives no leaks. Texts are read whole.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import BROADCAST_ROWS, fresh_names, shared_table, without
from .windows import let, starts, window_hashes

NUMBER, UNIT, NAME, INITIAL = "", "", "", ""
MARKS = f"[{NUMBER}-{INITIAL}]"
# Units that may follow a number.
UNITS = ("km", "m", "cm", "mm", "mi", "miles", "mile", "ft", "feet", "inches", "inch", "kg", "g", "mg", "lb", "lbs", "tons", "ton", "l", "ml", "s", "sec", "seconds", "second", "min", "minutes",
         "minute", "h", "hours", "hour", "days", "day", "weeks", "week", "months", "month", "years", "year", "dollars", "dollar", "euros", "euro", "cents", "percent", "degrees", "mph", "kmh", "kwh",
         "gb", "mb", "kb", "hz", "khz", "mhz", "ghz", "w", "kw", "v", "a", "n", "j", "pa")


def valued_text(text: Column) -> Column:
    """Words parted by single blanks; placeholders are a marker followed by the value."""
    t = F.regexp_replace(F.coalesce(text, F.lit("")), MARKS, " ")
    t = F.regexp_replace(t, r"(?<=[\p{L},;:] )(\p{Lu}\p{Ll}+)(?!\p{L})", NAME + "$1")
    t = F.regexp_replace(t, rf"(?<![\p{{L}}\p{{N}}_{NAME}])(\p{{Lu}}\p{{Ll}}+)(?!\p{{L}})", INITIAL + "$1")
    t = F.lower(t)
    digits = t.rlike(r"\d")
    n = F.regexp_replace(t, r"(?<=\d)[.,:/](?=\d)", "_")
    n = F.regexp_replace(n, rf"(?<![\p{{L}}\d_])(\d[\d_]*) ?({'|'.join(sorted(UNITS, key=len, reverse=True))})(?!\p{{L}})", f" {NUMBER}$1 {UNIT}$2 ")
    n = F.regexp_replace(n, r"(?<![\p{L}\d_" + NUMBER + r"])(\d[\d_]*)", f" {NUMBER}$1 ")
    t = F.when(digits, n).otherwise(t)
    return F.trim(F.regexp_replace(t, rf"[^\p{{L}}\p{{N}}_{NUMBER}-{INITIAL}]+", " "))


def canonical_text(text: Column) -> Column:
    """Words parted by single blanks, placeholders without their values, every capitalised word read as a name."""
    t = let(F.coalesce(text, F.lit("")), lambda x: F.when(x.rlike(MARKS), F.regexp_replace(x, MARKS, " ")).otherwise(x))
    t = F.lower(F.regexp_replace(t, r"(?=\p{Lu})(?<![\p{L}\p{N}_])\p{Lu}\p{Ll}+(?!\p{L})[\p{N}_]*", NAME))

    def numbers(x: Column) -> Column:
        n = F.regexp_replace(x, r"(?<=\d)[.,:/](?=\d)", "_")
        n = F.regexp_replace(n, rf"(?<![\p{{L}}\d_])(?:\d[\d_]*) ?(?:{'|'.join(sorted(UNITS, key=len, reverse=True))})(?!\p{{L}})", f" {NUMBER} {UNIT} ")
        n = F.regexp_replace(n, r"(?<![\p{L}\d_])(?:\d[\d_]*)", f" {NUMBER} ")
        return F.when(x.rlike(r"\d"), n).otherwise(x)

    return F.trim(F.regexp_replace(let(t, numbers), rf"[^\p{{L}}\p{{N}}_{NUMBER}-{INITIAL}]+", " "))


def canonical_hashes(text: Column) -> Column:
    """A hash per word of the canonical text, as `parsed` has them for the reading of capitals as names."""
    return let(canonical_text(text), lambda t: F.when(t == "", F.array().cast("array<bigint>")).otherwise(F.transform(F.split(t, " "), lambda w: F.xxhash64(w))))


def item_keys(items: DataFrame, id_col: str, text_col: str, width: int) -> DataFrame:
    """width, hash: the windows by which a text that holds an item is noticed. A capital at a sentence start is read as a name and as a
    plain word, and the item's first word as a name too, as it may start a sentence of the text."""
    name = F.array(F.xxhash64(F.lit(NAME)))
    first = lambda words: F.concat(name, F.slice(words, 2, F.greatest(F.size(words) - 1, F.lit(0))))
    rows = items.select(let(parsed(valued_text(F.col(text_col))), lambda r: F.struct(r["plain"].alias("plain"), r["named"].alias("named"))).alias("r")).select("r.*")
    rows = rows.filter(F.size("plain") > 0).select(F.explode(F.array("plain", "named", first(F.col("plain")), first(F.col("named")))).alias("words"))
    rows = rows.withColumn("width", F.least(F.size("words"), F.lit(width)))
    at = F.sequence(F.lit(0), F.size("words") - F.col("width"))
    return rows.select("width", F.explode(F.transform(at, lambda i: F.xxhash64(F.slice("words", i + 1, F.col("width"))))).alias("hash")).distinct()


def noticed(docs: DataFrame, keys: DataFrame, widths: list[int], few: bool, id_col: str, text_col: str) -> DataFrame:
    """id, key, text of the documents that hold a window of an item. Only hashes of windows are made of all the others; equal texts have one key."""
    key = F.xxhash64(F.coalesce(text_col, F.lit(""))).alias("key")
    if len(widths) == 1:
        found = docs.select(key, F.explode(let(canonical_hashes(F.col(text_col)), lambda own: window_hashes(own, widths[0]))).alias("hash")).withColumn("width", F.lit(widths[0]))
    else:
        every = let(canonical_hashes(F.col(text_col)), lambda own: F.array(*(F.struct(F.lit(w).alias("width"), window_hashes(own, w).alias("h")) for w in widths)))
        found = docs.select(key, F.explode(every).alias("x")).select("key", "x.width", F.explode("x.h").alias("hash"))
    hits = shared_table(found.join(F.broadcast(keys) if few else keys, ["width", "hash"], "left_semi").select("key").distinct())
    bounded = hits.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS
    own = docs.select(F.col(id_col).cast("long").alias("id"), key, F.coalesce(text_col, F.lit("")).alias("text"))
    return shared_table(own.join(F.broadcast(hits) if bounded else hits, "key", "left_semi").select("id", "key", "text"))


def parsed(valued: Column) -> Column:
    """Per word, read with a sentence-initial capital as a plain word and as a name: hash of the canonical word, and value of a placeholder (else null)."""
    def build(v: Column) -> Column:
        words = F.filter(F.split(v, " "), lambda w: w != "")
        word_hash = lambda w: F.xxhash64(F.when(w.rlike("^" + MARKS), F.substring(w, 1, 1)).otherwise(w))
        value = lambda w: F.when(w.rlike("^" + MARKS), w)
        plain, named = (F.transform(words, lambda w: F.regexp_replace(w, "^" + INITIAL, to)) for to in ("", NAME))  # noqa: B023
        plain, named = F.when(v.contains(INITIAL), plain).otherwise(words), F.when(v.contains(INITIAL), named).otherwise(words)
        return let(F.struct(plain.alias("plain"), named.alias("named")), lambda r: F.struct(
            F.transform(r["plain"], word_hash).alias("plain"), F.transform(r["plain"], value).alias("plain_value"), F.transform(r["named"], word_hash).alias("named"), F.transform(r["named"], value).alias("named_value")))

    return let(valued, build)


def windows_of(row: Column, width: int) -> Column:
    """pos, reading, hash, slots (values of the placeholders inside, in order) of each window of a parsed text.

    reading: 'both' if no sentence-initial capital is inside; else one window for each reading of it, 'plain' and 'named'.
    """
    part = lambda c, i: F.slice(row[c], i + 1, width)
    differ = lambda i: part("plain", i) != part("named", i)
    made = lambda i, c, reading: F.struct(i.alias("pos"), reading.alias("reading"), F.xxhash64(part(c, i)).alias("hash"), F.array_join(part(f"{c}_value", i), " ").alias("slots"))
    at = starts(F.size(row["plain"]), width)
    plain = F.transform(at, lambda i: made(i, "plain", F.when(differ(i), F.lit("plain")).otherwise(F.lit("both"))))
    return F.concat(plain, F.transform(F.filter(at, differ), lambda i: made(i, "named", F.lit("named"))))


def windows(rows: DataFrame, widths: list[int], id_col: str, text_col: str) -> DataFrame:
    """id, width, pos, reading, hash, slots of all windows of the given widths; each text is parsed once."""
    def every(row: Column) -> Column:
        return F.array(*(F.struct(F.lit(w).alias("width"), windows_of(row, w).alias("w")) for w in widths))

    parts = rows.select(F.col(id_col).cast("long").alias("id"), valued_text(F.col(text_col)).alias("v"))
    if len(widths) == 1:
        found = parts.select("id", F.lit(widths[0]).alias("width"), F.explode(let(parsed(F.col("v")), lambda row: windows_of(row, widths[0]))).alias("w"))
    else:
        by_width = parts.select("id", F.explode(let(parsed(F.col("v")), every)).alias("x"))
        found = by_width.select("id", "x.width", F.explode("x.w").alias("w"))
    return found.select("id", "width", "w.pos", "w.reading", "w.hash", "w.slots")


def benchmark_windows(benchmark: DataFrame, width: int, id_col: str, text_col: str) -> DataFrame:
    """item_id, width, item_pos, reading, hash, item_slots, item_windows; an item shorter than `width` is one window of its own width."""
    sized = benchmark.select(F.col(id_col).alias("id"), F.col(text_col).alias("t"), F.size(parsed(valued_text(F.col(text_col)))["plain"]).alias("n"))
    sized = shared_table(sized.filter("n > 0"))
    lengths = sorted(r["w"] for r in sized.select(F.least("n", F.lit(width)).alias("w")).distinct().collect())
    made = [windows(sized.filter(F.least("n", F.lit(width)) == w), [w], "id", "t") for w in lengths or [width]]
    rows = reduce(DataFrame.union, made).select(F.col("id").alias("item_id"), "width", F.col("pos").alias("item_pos"), "reading", "hash", F.col("slots").alias("item_slots"))
    rows = rows.dropDuplicates(["item_id", "width", "item_pos", "reading"])
    totals = rows.groupBy("item_id").agg(F.countDistinct("item_pos").alias("item_windows"))
    return shared_table(rows.join(totals, "item_id"))


def leaks(docs: DataFrame, benchmark: DataFrame, width: int = 8, coverage: float = 0.5, run: int = 13, broadcast_rows: int = 1_000_000,
          id_col: str = "doc_id", text_col: str = "text", item_id: str = "item_id", item_text: str = "text") -> DataFrame:
    """doc_id, item_id, item_windows, matched_windows, coverage, n_slots, changed_slots, kind of each leak."""
    items = benchmark_windows(benchmark, width, item_id, item_text)
    widths = {r["width"]: r["count"] for r in items.groupBy("width").count().collect()}
    few, sizes = sum(widths.values()) <= broadcast_rows, sorted(widths) or [width]
    seen = noticed(docs, item_keys(benchmark, item_id, item_text, width), sizes, few, id_col, text_col)
    texts = seen.select("key", "text").dropDuplicates(["key"])
    hits = windows(texts, sizes, "key", "text").drop("reading").join(F.broadcast(items) if few else items, ["width", "hash"])
    found = leaking(hits, coverage, run)
    rows = seen.select(F.col("id").alias("doc_id"), F.col("key").alias("text_key")).join(found.withColumnRenamed("doc_id", "text_key"), "text_key").drop("text_key")
    facts = ["item_windows", "matched_windows", "coverage", "n_slots", "changed_slots", "kind"]
    best_of = F.max(F.struct("matched_windows", "item_windows", "coverage", "n_slots", "changed_slots", "kind")).alias("b")
    return rows.groupBy("doc_id", "item_id").agg(best_of).select("doc_id", "item_id", *(f"b.{c}" for c in facts))


def leaking(hits: DataFrame, coverage: float, run: int) -> DataFrame:
    """doc_id, item_id, … of the leaks among matching windows (id, item_id, item_windows, item_pos, item_slots, reading, pos, slots)."""
    pair, enough = ["doc_id", "item_id", "item_windows"], (F.col("matched_windows") >= coverage * F.col("item_windows")) | (F.col("matched_windows") >= run)
    # Windows without values agree with every placement; the others belong to the placement of their offset.
    offset = F.when(F.col("item_slots") != "", F.col("pos") - F.col("item_pos"))
    placed = hits.select(F.col("id").alias("doc_id"), *pair[1:], offset.alias("offset"), F.struct("item_pos", "item_slots", "slots", "reading").alias("w"))
    placed = shared_table(placed.groupBy(*pair, "offset").agg(F.collect_set("w").alias("w")))  # several aggregations follow; the windows are made once
    each = placed.select(*pair, "offset", F.explode("w").alias("w")).select(*pair, "w.item_pos", F.struct("offset", "w").alias("at"), (F.col("w.item_slots") == F.col("w.slots")).alias("same"))
    found = each.groupBy(*pair, "item_pos").agg(F.min(F.when(F.col("at.w.reading") != "named", F.col("at"))).alias("first"), F.min(F.when(F.col("same"), F.col("at"))).alias("equal"))
    found = found.groupBy(*pair).agg(F.count(F.lit(1)).alias("matched_windows"), F.collect_list("first.w").alias("first"), F.collect_list("equal.w").alias("equal"))
    found = shared_table(found.filter(enough).drop("matched_windows"))
    # The windows whose values equal the item's, the first places, and the places of each offset by each reading.
    free = lambda w, other: F.size(F.filter(w, lambda x: (x["item_slots"] == "") & (x["reading"] != other)))
    slotted = lambda w, other: F.filter(w, lambda x: (x["item_slots"] != "") & (x["reading"] != other))
    mine = [F.col(c).alias(f"of_{c}") for c in pair]
    same_pair = F.col("doc_id").eqNullSafe(F.col("of_doc_id")) & (F.col("item_id") == F.col("of_item_id"))
    reading = lambda w: F.explode(F.array(*(F.struct(free(F.col("first"), other).alias("n_free"), slotted(w, other).alias("w")) for other in ("named", "plain")))).alias("c")
    by_offset = placed.filter("offset is not null").select(*pair, "w").join(found.select(*mine, "first"), same_pair).select(*pair, reading(F.col("w")))
    by_pair = found.select(*pair, F.explode(F.array(*(F.struct(free(F.col(c), other).alias("n_free"), slotted(F.col(c), other).alias("w")) for c, other in (("first", "named"), ("equal", "none"))))).alias("c"))
    each = by_pair.union(by_offset).select(*pair, "c.n_free", "c.w")
    choices = each.select(*pair, "n_free", F.sort_array(F.array_distinct(F.transform("w", lambda x: x["item_pos"]))).alias("positions"), values_of(F.col("w")).alias("values"))
    choices = shared_table(choices.filter(agree(F.col("values"))).distinct())
    single = best(choices, pair).filter(enough)
    # Text put into a passage parts it into several offsets: placements that agree are joined, from each of them in turn.
    rest = choices.join(single.select(*mine), same_pair, "left_anti").groupBy(*pair, "n_free").agg(F.sort_array(F.collect_set(F.struct(F.size("positions").alias("n"), "positions", "values")), asc=False).alias("all"))
    rest = rest.filter(F.size("all") > 1).select(*pair, "n_free", F.explode(F.transform("all", lambda seed: joined(seed, F.col("all")))).alias("c")).select(*pair, "n_free", "c.positions", "c.values")
    kept = single.union(best(rest, pair).filter(enough))
    return kept.select("doc_id", "item_id", "item_windows", "matched_windows", (F.col("matched_windows") / F.col("item_windows")).alias("coverage"), "n_slots", "changed_slots",
                       F.when(F.col("changed_slots") > 0, "reparameterised").otherwise("verbatim").alias("kind"))


def values_of(found: Column) -> Column:
    """The distinct 'value of the item, value of the document' of windows (item_slots, slots)."""
    of = lambda x: F.zip_with(F.split(x["item_slots"], " "), F.split(x["slots"], " "), lambda i, d: F.concat(i, F.lit(" "), d))
    return F.sort_array(F.array_distinct(F.flatten(F.transform(found, of))))


def agree(values: Column) -> Column:
    """Whether every value of the item has one value of the document."""
    return F.size(F.array_distinct(F.transform(values, lambda v: F.substring_index(v, " ", 1)))) == F.size(values)


def joined(seed: Column, others: Column) -> Column:
    """The seed (positions, values) with all others that agree with what is joined so far."""
    def step(a: Column, x: Column) -> Column:
        both = F.array_union(a["values"], x["values"])
        return F.when(agree(both), F.struct(F.array_union(a["positions"], x["positions"]).alias("positions"), both.alias("values"))).otherwise(a)

    return F.aggregate(others, F.struct(seed["positions"].alias("positions"), seed["values"].alias("values")), step)


def best(choices: DataFrame, pair: list[str]) -> DataFrame:
    """The choice of most windows for each document and item; of equally many, the one that changes the fewest values."""
    changed = F.size(F.filter("values", lambda v: F.substring_index(v, " ", 1) != F.substring_index(v, " ", -1)))
    rated = F.struct((F.col("n_free") + F.size("positions")).cast("long").alias("n"), (-changed).cast("long").alias("kept"), F.size("values").cast("long").alias("n_slots"))
    top = choices.groupBy(*pair).agg(F.max(rated).alias("b"))
    return top.select(*pair, F.col("b.n").alias("matched_windows"), F.col("b.n_slots").alias("n_slots"), (-F.col("b.kept")).alias("changed_slots"))


def drop_leaks(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """The documents without a leak, with their columns. Rows without an id stay."""
    id_col, (own,) = options.get("id_col", "doc_id"), fresh_names(docs, 1)
    gone = shared_table(leaks(docs, benchmark, **options).filter("doc_id is not null").select(F.col("doc_id").alias(own)).distinct())
    return without(docs.withColumn(own, F.col(id_col).cast("long")), gone, [own]).select(*(f"`{c}`" for c in docs.columns))
