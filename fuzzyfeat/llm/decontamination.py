"""Benchmark decontamination by template windows, in DataFrame functions only.

A text's template replaces numbers, units after numbers and names by typed placeholders, lower-cases the rest and drops
punctuation. A name is a run of capitalised words that are no usual openers of a sentence, wherever it stands, so a
passage has the same template at the head of a sentence as inside one; the run is one slot, however many words it has. Windows of WINDOW template words are hashed and joined by hash
with those of the benchmark, so a question asked again with other numbers or names meets its original. Matched windows of
one document and item on one diagonal form a candidate. A name of the item must stand for one name of the document, and
different names for different ones: of pairs that disagree the most frequent holds, none if several are, and the windows
that hold another pair are taken out. Numbers and units may change as they like, to equal ones too.

Diagonals of a document and item that lie near each other, as words put in or left out make them, count as one: nearer
than NEIGHBOURS, and than the item is long, so that copies of an item one after the other stay apart. A document is
contaminated by an item if their consistent windows together cover at least MIN_COVERAGE of the item's windows, or
LONG_RUN of them, or if EXACT_RUN words of the item, of which one window matches, stand in it as they are. Only windows of at least LEAST_LITERALS different literal words are matched and counted.
Items with fewer than FEW_WINDOWS of those, such as items of fewer than WINDOW words, are also looked for word by word,
whole and with their own values, however short they are; the windows of such a row are 0. Null and empty texts match nothing; rows without doc_id are not reported. Repeated rows of a
document count once. Empty tables give an empty result.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from fuzzyfeat.session import materialise

WINDOW, LEAST_LITERALS, MIN_COVERAGE, LONG_RUN = 8, 4, 0.4, 12
EXACT_RUN, NEIGHBOURS = 13, 64
KEY_WORDS, MOST_KEYS = 2, 20_000
DOC = ["doc_id", "version"]  # rows that share an id but not the text are documents of their own until the end
FEW_WINDOWS = 4  # so few windows tell little of an item that has more of them
BROADCAST_ROWS, BROADCAST_IDS = 500_000, 500_000
NAME, NUMBER, UNIT, JOINT = (chr(0xE000 + i) for i in range(4))  # private-use characters: no text word is one of them
#: Fixed list of units.
UNITS = "mm cm dm m km in ft yd mi mg g kg t lb lbs oz ml cl dl l gal ms s sec min h hr hrs hour hours day days week weeks month months year years usd eur gbp dollars euros cents percent kb mb gb tb hz khz mhz ghz w kw v a j kj cal kcal c f k meters metres miles grams liters litres seconds minutes".split()

#: Usual openers of a sentence or a question, in four languages: never names.
OPENERS = (
    "The This That These Those There Then Than They Their He Him His She Her Hers It Its We Us Our You Your My Me An And Any All Also After Although Are As At Be Because Before Being Both But By Can Could Did Do Does Each Either Every Few Find For From Given Give Had Has Have Here How However If In Into Is Let Like Many May More Most Much Must No Nor Not Now Of On Once One Only Or Other Out Over Prove Please Read Show Since So Solve Some Such Suppose Tell To Today Two Under Until Use Was Were What When Where Whether Which While Who Whom Whose Why Will With Would Write Yes Yet Answer Calculate Choose Compute Consider Complete Describe Determine Evaluate Explain List Name Select Simplify Question Assume During "
    "El La Los Las Un Una Unos Unas De Del Que Qué Se Si Sin Su Sus Es Son En Con Como Cómo Cual Cuál Cuando Cuándo Cuanto Cuántos Cuántas Donde Dónde Por Para Pero No Ni Lo Le Les Al Este Esta Esto Ese Esa Hay Ha Más Muy Ya Yo Quien Quién Entre Sobre "
    "Le Les Une Des Du Et Est Ce Cet Cette Ces Dans Il Elle Ils Elles Je Nous Vous Tu On Ou Où Qui Quoi Quel Quelle Quand Comment Combien Pourquoi Pour Par Sur Sous Avec Sans Mais Ne Pas Plus Son Sa Ses Leur Leurs Au Aux Si Comme "
    "Der Die Das Den Dem Ein Eine Einen Einem Einer Und Oder Aber Ist Sind War Wer Wie Was Wann Wo Warum Wenn Weil Als Auch Auf Aus Bei Bis Da Dann Dass Durch Er Es Sie Ich Wir Ihr Im In Mit Nach Nicht Noch Nun Nur Ob So Um Von Vor Wird Zu Zum Zur Viele Wieviel Welche Welcher Welches Für Über"
).split()


def _any_of(words: list[str]) -> str:
    """A pattern for any of the words that tests their common beginnings once."""
    tree: dict = {}
    for word in words:
        node = tree
        for c in word:
            node = node.setdefault(c, {})
        node[""] = {}

    def arms(node: dict) -> str:
        below = [re.escape(c) + arms(n) for c, n in sorted(node.items()) if c]
        if not below:
            return ""
        return f"(?:{'|'.join(below)})" + "?" * ("" in node)

    return arms(tree)


#: A word of a name. The cheap test of the capital comes first. Repeated groups are possessive: Java's engine goes through
#: them in a loop, and through others by a call for each repetition, which a long run of names takes beyond the stack.
_NAME_PART = r"\p{Lu}\p{Ll}++(?![\p{L}\p{N}])"
_NAME_WORD = rf"(?=\p{{Lu}})(?<![\p{{L}}\p{{N}}])(?!{_any_of(OPENERS)}(?![\p{{L}}\p{{N}}])){_NAME_PART}(?:-{_NAME_PART})*+"


def _bound(value: Column, f) -> Column:
    """f of a value that is computed once a row, however often f names it."""
    return F.get(F.transform(F.array(value), f), F.lit(0))


def _words(text: Column) -> Column:
    """Lower case, punctuation dropped, split at white space."""
    bare = F.regexp_replace(F.lower(text), r"[^a-z \p{L}\p{N}\x{E000}-\x{E003}\s]+", "")
    return F.array_remove(F.split(bare, r"\s+"), "")


def template_words(text: Column) -> Column:
    """Words of the template; word for word beside value_words of the same text."""
    named = F.regexp_replace(text, rf"{_NAME_WORD}(?:\s+{_NAME_WORD})*+", NAME)
    numbered = F.regexp_replace(named, r"[+-]?\p{Nd}(?:[\p{Nd}.,]*\p{Nd})?", NUMBER)
    units = lambda t: F.when(F.contains(t, F.lit(NUMBER)), F.regexp_replace(t, rf"({NUMBER}\s*)(?i:{_any_of(UNITS)})(?![\p{{L}}\p{{N}}])", f"$1{UNIT}")).otherwise(t)
    return _words(_bound(numbered, units))


def value_words(text: Column) -> Column:
    """The words as they stand, word for word beside the template's: inside a number, what separates digits goes, and JOINT joins the words of a name."""
    joined = F.regexp_replace(text, rf"({_NAME_WORD})\s+(?={_NAME_WORD})", f"$1{JOINT}")
    return _words(F.regexp_replace(joined, r"(?<=\p{Nd})[.,](?=\p{Nd})", ""))


def _joints(values: Column) -> Column:
    """The places of joined words in value_words, once for each joint: what a place lacks to that in the text's own words."""
    at = lambda w, i: F.array_repeat(i, F.length(w) - F.length(F.replace(w, F.lit(JOINT), F.lit(""))))
    return F.flatten(F.transform(values, at))


def _in_text(place: Column, joints: str = "joints") -> Column:
    """A place among the template's words as a place among the text's own words."""
    return (place + F.size(F.filter(joints, lambda j: j < place))).cast("long")


def windows_at(words: Column, window: int, keys: list[int] | None = None, key_words: int = 1) -> Column:
    """Array of (at, h): the hash of each run of `window` words. keys: only of runs whose first key_words words have one of these hashes."""

    def starts(ws: Column) -> Column:
        every = F.when(F.size(ws) >= window, F.sequence(F.lit(0), F.size(ws) - window)).otherwise(F.array().cast("array<int>"))
        return every if keys is None else F.filter(every, lambda i: F.xxhash64(*(F.get(ws, i + j) for j in range(key_words))).isin(keys))

    return _bound(words, lambda ws: F.transform(starts(ws), lambda i: F.struct(i.alias("at"), F.xxhash64(F.slice(ws, i + 1, window)).alias("h"))))


def _slots(words: Column) -> Column:
    return F.filter(words, lambda w: ~w.isin(NAME, NUMBER, UNIT))


def benchmark_windows(benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """(h, key, item_id, item_at, item_windows, all_windows) of the windows that say enough to match; item_windows counts these. key: the hash of their first two words."""
    items = benchmark.filter(F.col("item_id").isNotNull() & F.col("text").isNotNull()).select("item_id", template_words(F.col("text")).alias("words")).distinct()
    telling = F.filter("hashes", lambda w: F.size(F.array_distinct(_slots(F.slice("words", w["at"] + 1, window)))) >= LEAST_LITERALS)
    items = items.select("item_id", "words", windows_at(F.col("words"), window).alias("hashes")).withColumn("telling", telling)
    each = items.select("item_id", "words", F.size("telling").alias("item_windows"), F.size("hashes").alias("all_windows"), F.explode("telling").alias("w"))
    return each.select("w.h", F.xxhash64(*(F.get("words", F.col("w.at") + j) for j in range(min(KEY_WORDS, window)))).alias("key"), "item_id", F.col("w.at").alias("item_at"), "item_windows", "all_windows")


def _keys(wanted: DataFrame) -> list[int] | None:
    """The keys of the wanted windows as numbers of the plan, if they are few enough; None: every window of a document goes to the join."""
    keys = [r["key"] for r in wanted.select("key").distinct().limit(MOST_KEYS + 1).collect()]
    return keys if len(keys) <= MOST_KEYS else None


def text_words(text: Column) -> Column:
    """The text's own words, names in single words, numbers as in value_words."""
    return _words(F.regexp_replace(text, r"(?<=\p{Nd})[.,](?=\p{Nd})", ""))


def whole_items(docs: DataFrame, benchmark: DataFrame, wanted: DataFrame, window: int = WINDOW) -> DataFrame:
    """(doc_id, item_id, first_word, last_word): the first verbatim copy in a document of each item that has few windows or none.

    The first words of an item, `window` at most, are its key: documents are hashed for the lengths of keys that occur.
    """
    enough = wanted.filter(F.col("item_windows") >= FEW_WINDOWS).select("item_id").distinct()
    items = benchmark.filter("item_id IS NOT NULL AND text IS NOT NULL").join(enough, "item_id", "left_anti").select("item_id", text_words(F.col("text")).alias("item_text")).filter(F.size("item_text") > 0).distinct()
    items = items.withColumn("n", F.least(F.size("item_text"), F.lit(window)))
    items = materialise(items.withColumn("h", F.xxhash64(F.slice("item_text", F.lit(1), F.col("n")))))
    lengths = [r["n"] for r in items.select("n").distinct().collect()]  # `window` numbers at most
    if not lengths:
        return wanted.filter(F.lit(False)).select(F.lit(None).cast("long").alias("doc_id"), "item_id", *(F.lit(None).cast("long").alias(c) for c in ("first_word", "last_word")))
    few = F.broadcast(items) if items.count() <= BROADCAST_ROWS else items
    keys = _keys(items.withColumn("key", F.xxhash64(F.get("item_text", F.lit(0)))))
    of_length = lambda ws, n: F.transform(windows_at(ws, n, keys), lambda w: F.struct(F.lit(n).alias("n"), w["at"].alias("at"), w["h"].alias("h")))
    hashes = lambda ws: F.flatten(F.array(*(of_length(ws, n) for n in lengths)))
    rows = docs.select(*DOC, F.explode(_bound(text_words(F.col("text")), hashes)).alias("e"))
    met = materialise(rows.select(*DOC, "e.*").join(few.drop("item_text"), ["n", "h"]).select(*DOC, "item_id", "at").distinct())
    ids = met.select("doc_id").distinct()
    held = docs.join(F.broadcast(ids) if met.count() <= BROADCAST_IDS else ids, "doc_id", "left_semi").dropDuplicates(DOC).select(*DOC, text_words(F.col("text")).alias("doc_text"))
    size = F.size("item_text")
    same = met.join(held, DOC).join(few.select("item_id", "item_text"), "item_id").filter(F.slice("doc_text", F.col("at") + 1, size) == F.col("item_text"))
    place = F.min(F.struct(F.col("at").cast("long").alias("first_word"), (F.col("at") + size).cast("long").alias("last_word")))
    return same.groupBy("doc_id", "item_id").agg(place.alias("e")).select("doc_id", "item_id", "e.*")


def _longest_run(ours, theirs) -> Column:
    """(words, low, high): the longest run of the item's words that the document has on the diagonal; words counts those of the text."""
    size = F.size("item_values")
    differ = F.filter(F.sequence(F.lit(-1), size), lambda i: (i < 0) | (i >= size) | ~ours(i).eqNullSafe(theirs(i)))

    def longest(breaks: Column) -> Column:
        def run(j: Column) -> Column:
            low, high = F.get(breaks, j - 1) + 1, F.get(breaks, j)
            joints = F.size(F.filter(_joints(F.col("item_values")), lambda i: (low <= i) & (i < high)))
            return F.struct((high - low + joints).alias("words"), low.alias("low"), high.alias("high"))

        return F.array_max(F.transform(F.sequence(F.lit(1), F.size(breaks) - 1), run))

    return F.get(F.transform(F.array(differ), longest), F.lit(0))


def without_breaches(rows: DataFrame, window: int = WINDOW) -> DataFrame:
    """The rows with only those places whose windows hold no name that stands for another one elsewhere on neighbouring diagonals."""
    keys = [*DOC, "item_id", "part"]
    pairs = rows.select(*keys, "diagonal", F.explode("names").alias("p")).select(*keys, "diagonal", "p.*")
    counted = pairs.groupBy(*keys, "a", "b").agg(F.count("*").alias("n"))
    for c in ("a", "b"):
        side = Window.partitionBy(*keys, c)
        counted = counted.withColumn(f"most_{c}", F.max("n").over(side))
        counted = counted.withColumn(f"ties_{c}", F.count(F.when(F.col("n") == F.col(f"most_{c}"), 1)).over(side))
    holds = (F.col("n") == F.col("most_a")) & (F.col("n") == F.col("most_b")) & (F.col("ties_a") == 1) & (F.col("ties_b") == 1)
    breaches = pairs.join(counted.filter(~holds).select(*keys, "a", "b"), [*keys, "a", "b"]).groupBy(*keys, "diagonal").agg(F.collect_set("at").alias("breaches"))
    places = F.filter("places", lambda p: ~F.exists(F.coalesce("breaches", F.array().cast("array<int>")), lambda i: (p <= i) & (i < p + window)))
    return rows.join(breaches, [*keys, "diagonal"], "left").withColumn("places", places).drop("breaches", "names")


def contaminated(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, min_coverage: float = MIN_COVERAGE, long_run: int = LONG_RUN, exact_run: int = EXACT_RUN) -> DataFrame:
    """(doc_id, item_id, windows, coverage, exact, first_word, last_word): a row for each document and item that contaminates it.

    exact: the slots of all matched windows hold the item's own values. first_word and last_word: where the windows and runs of the best diagonals begin and end.
    """
    wanted = materialise(benchmark_windows(benchmark, window))
    small = wanted.count() <= BROADCAST_ROWS
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").filter("doc_id IS NOT NULL AND text IS NOT NULL").withColumn("version", F.xxhash64("text"))
    rows = texts.select(*DOC, F.explode(windows_at(template_words(F.col("text")), window, _keys(wanted), min(KEY_WORDS, window))).alias("e")).select(*DOC, "e.*")
    wanted = wanted.drop("key")
    met = rows.join(F.broadcast(wanted) if small else wanted, "h").withColumn("diagonal", F.col("at") - F.col("item_at"))
    met = met.groupBy(*DOC, "item_id", "diagonal").agg(F.max("item_windows").alias("item_windows"), F.max("all_windows").alias("all_windows"), F.collect_set("item_at").alias("places"))
    order = Window.partitionBy(*DOC, "item_id").orderBy("diagonal")
    apart = F.col("diagonal") - F.lag("diagonal").over(order) >= F.least(F.lit(NEIGHBOURS), F.col("all_windows") + (window - 1))
    met = materialise(met.withColumn("apart", F.coalesce(apart.cast("int"), F.lit(0))).withColumn("part", F.sum("apart").over(order)).drop("apart"))
    # Slot consistency, for the few documents that met an item at all.
    ids = met.select("doc_id").distinct()
    ids = F.broadcast(ids) if met.count() <= BROADCAST_IDS else ids
    held = texts.join(ids, "doc_id", "left_semi").dropDuplicates(DOC).select(*DOC, value_words(F.col("text")).alias("doc_values")).withColumn("joints", _joints(F.col("doc_values")))
    items = benchmark.select("item_id", template_words(F.col("text")).alias("item_words"), value_words(F.col("text")).alias("item_values")).distinct()
    both = met.join(held, DOC).join(F.broadcast(items) if small else items, "item_id")
    inside = F.array_distinct(F.flatten(F.transform("places", lambda p: F.sequence(p, p + (window - 1)))))
    ours, theirs = (lambda i: F.get("item_values", i)), (lambda i: F.get("doc_values", i + F.col("diagonal")))
    names = F.transform(F.filter("inside", lambda i: F.get("item_words", i) == NAME), lambda i: F.struct(i.alias("at"), ours(i).alias("a"), theirs(i).alias("b")))
    changed = F.filter("inside", lambda i: F.get("item_words", i).isin(NAME, NUMBER, UNIT) & ~ours(i).eqNullSafe(theirs(i)))
    both = both.withColumn("inside", inside).withColumn("names", names).withColumn("changed", changed)
    both = both.withColumn("run", _longest_run(ours, theirs))
    both = without_breaches(materialise(both.select(*met.columns, "joints", "names", "changed", "run")), window)
    shown = lambda c: F.when(F.col("run.words") >= exact_run, F.col(f"run.{c}"))
    low = F.col("diagonal") + F.least(F.array_min("places"), shown("low"))
    high = F.col("diagonal") + F.greatest(F.array_max("places") + window, shown("high"))
    found = both.withColumn("first_word", _in_text(low)).withColumn("last_word", _in_text(high)).groupBy(*DOC, "item_id", "part").agg(
        F.size(F.array_distinct(F.flatten(F.collect_list("places")))).cast("long").alias("windows"), F.max("item_windows").alias("item_windows"), F.max("all_windows").alias("all_windows"),
        F.bool_and(F.size("changed") == 0).alias("exact"), F.min("first_word").alias("first_word"), F.max("last_word").alias("last_word"), F.max("run.words").alias("run"),
    )
    covered = (F.col("windows") >= min_coverage * F.col("item_windows")) & (F.col("windows") >= F.least(F.lit(FEW_WINDOWS), min_coverage * F.col("all_windows")))
    found = found.filter(covered | (F.col("windows") >= long_run) | (F.col("run") >= exact_run)).select("doc_id", "item_id", "windows", (F.col("windows") / F.col("item_windows")).alias("coverage"), "exact", "first_word", "last_word")
    best = F.max_by(F.struct("windows", "coverage", "exact", "first_word", "last_word"), F.struct("windows", -F.col("first_word"))).alias("best")
    whole = whole_items(texts, benchmark, wanted, window).select("doc_id", "item_id", F.lit(0).cast("long").alias("windows"), F.lit(1.0).alias("coverage"), F.lit(True).alias("exact"), "first_word", "last_word")
    return found.unionByName(whole).groupBy("doc_id", "item_id").agg(best).select("doc_id", "item_id", "best.*")


def decontaminate(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The documents that no item contaminates, as they came."""
    bad = materialise(contaminated(docs, benchmark).select("doc_id").distinct())
    return docs.join(F.broadcast(bad) if bad.count() <= BROADCAST_IDS else bad, "doc_id", "left_anti").select(docs.columns)
