"""Benchmark decontamination by template canonicalisation, in Spark expressions alone.

Texts become words with numbers, units and names replaced by typed placeholders, so a question asked again with other
values keeps its template. Names are told by their capital letter inside a sentence, units by standing after a number or
in a list, numbers by digits or number words. Windows of template words are hash-joined with those of the benchmark, and a
match counts only if its slots are consistent: places that hold one value in the item hold one value in the document.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from tidegraph.runtime import materialize

#: Words of a window. Items with fewer words are matched as a whole.
WINDOW = 8
#: Units of measure and currency words that become a placeholder wherever they stand; any word of up to four letters glued to a number is a unit too. Fixed values.
UNITS = ("mm", "cm", "km", "kg", "mg", "lb", "lbs", "oz", "ml", "mph", "kmh", "usd", "eur", "gbp", "dollars", "dollar", "euros", "euro", "pounds", "pound", "cents", "miles", "mile", "meters", "metres", "meter", "metre", "feet", "inches", "hours", "hour", "minutes", "minute", "seconds", "days", "weeks", "months", "years", "percent", "litres", "liters", "grams", "kilograms", "kilometers")
#: Number words. Fixed values.
NUMBERS = ("zero", "two", "three", "four", "five", "six", "seven", "eight", "nine", "ten", "eleven", "twelve", "thirteen", "fourteen", "fifteen", "sixteen", "seventeen", "eighteen", "nineteen", "twenty", "thirty", "forty", "fifty", "sixty", "seventy", "eighty", "ninety", "hundred", "thousand", "million", "billion", "dozen")
#: Given names that are names in any case and place; all others are told by their form. Fixed values.
NAMES = ("alice", "bob", "carol", "david", "emma", "frank", "grace", "henry", "jack", "james", "jane", "john", "julia", "kate", "laura", "lisa", "mark", "mary", "michael", "mike", "natalia", "paul", "peter", "robert", "sam", "sarah", "susan", "tom", "weng", "betty")
#: Benchmark windows that are sent to every executor; with more the join is shuffled.
BROADCAST_WINDOWS = 500_000
_BETWEEN = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: Stands before words that a capital letter inside a sentence, or a number glued to them, tells to be names or units. Private code points, which are no letters.
NAME_MARK, UNIT_MARK = "\ue000", "\ue001"


def let(value: Column, body) -> Column:
    """``body(value)`` with the value bound as a lambda argument, so that it is made once however often it is used."""
    return F.element_at(F.transform(F.array(value), body), 1)


def marked_words(text: Column) -> Column:
    """Lower-cased words, those with a capital letter inside a sentence and units glued to a number behind a mark.

    Thousands separators and decimals stay inside their number; marks that the text itself has are dropped.
    """
    t = F.coalesce(text, F.lit(""))
    t = F.when(t.rlike(f"[{NAME_MARK}{UNIT_MARK}]"), F.translate(t, NAME_MARK + UNIT_MARK, "")).otherwise(t)
    low = F.lower(F.regexp_replace(t, r"(?<=[\p{L}0-9,;)] )(?=[A-Z][a-z])", NAME_MARK))
    numbers = lambda x: F.regexp_replace(F.regexp_replace(x, r"(?<=[0-9])[.,](?=[0-9])", ""), r"(?<![0-9a-z])([0-9]+)([a-z]{1,4})(?![0-9a-z])", f"$1 {UNIT_MARK}$2")
    plain = let(low, lambda x: F.when(x.rlike("[0-9][.,]?[0-9a-z]"), numbers(x)).otherwise(x))
    return F.filter(F.split(plain, _BETWEEN), lambda w: w != "")


def bare(word: Column) -> Column:
    """The word without its mark."""
    return F.when(word >= NAME_MARK, F.ltrim(word, F.lit(NAME_MARK + UNIT_MARK))).otherwise(word)


def _is_number(word: Column) -> Column:
    return (word >= "0") & (word < ":") & word.rlike("^[0-9]+$")


def may_be_slot(word: Column) -> Column:
    """True for every word that has a placeholder (and for no others but those beyond the marks' code points)."""
    return word.isin(*NUMBERS, *UNITS, *NAMES) | (word >= NAME_MARK) | _is_number(word)


def placeholder(word: Column, named: Column) -> Column:
    """The typed placeholder of a marked word, or the word; ``named`` are the text's words that are marked as names."""
    name = word.startswith(NAME_MARK) | word.isin(*NAMES) | ((F.size(named) > 0) & F.array_contains(named, word))
    kind = F.when(_is_number(word) | word.isin(*NUMBERS), "<number>").when(word.startswith(UNIT_MARK) | word.isin(*UNITS), "<unit>").when(name, "<name>")
    return F.coalesce(kind, bare(word))


def _template(words: Column, body) -> Column:
    """``body(template words)`` for marked words."""
    named = F.array_distinct(F.transform(F.filter(words, lambda w: w.startswith(NAME_MARK)), bare))
    return let(named, lambda known: let(F.transform(words, lambda w: placeholder(w, known)), body))


def _hashes(words: Column, widths: list[int], suits) -> Column:
    """For each of ``widths`` that ``suits`` the number of words, the hashes of all windows; a window hashes the hashes of its words."""

    def of_width(hashed: Column, width: int) -> Column:
        n = F.size(hashed)
        every = F.transform(hashed, lambda h, i: F.xxhash64(h, *[F.get(hashed, i + k) for k in range(1, width)]))
        return F.when(suits(n, width), F.slice(every, F.lit(1), F.greatest(n - width + 1, F.lit(0)))).otherwise(F.array().cast("array<bigint>"))

    return let(F.transform(words, lambda w: F.xxhash64(w)), lambda hashed: F.array(*[of_width(hashed, w) for w in widths]))


def _long_enough(n: Column, width: int) -> Column:
    return n >= width


def _keys(rows: DataFrame, keys: list[str], text: Column, widths: list[int], suits) -> DataFrame:
    """(keys, key): the hashes of the text's windows as they stand and of their templates. No words or places go along."""
    plain = lambda words: F.flatten(_hashes(F.transform(words, bare), widths, suits))
    both = lambda words: F.concat(plain(words), _template(words, lambda t: F.flatten(_hashes(t, widths, suits))))
    made = let(marked_words(text), lambda words: F.when(F.exists(words, may_be_slot), both(words)).otherwise(F.flatten(_hashes(words, widths, suits))))
    return rows.select(*keys, F.explode(made).alias("key"))


def _windows(rows: DataFrame, keys: list[str], text: Column, widths: list[int], suits) -> DataFrame:
    """(keys, total, place, key, raw, slots) of each window of as many words as one of ``widths`` says, if it ``suits`` the text.

    ``key`` hashes a window's template words, ``raw`` its words as they were, and ``slots`` are the values behind its
    placeholders (null without any). A window with placeholders is also there under ``raw`` as its key, without slots, so
    that an item whose names stand in other case is found by its words.
    """

    def windows(r: Column, t: Column, rh: Column, th: Column) -> Column:
        def of_width(raws: Column, temps: Column, width: int) -> Column:
            slots = lambda i: F.transform(F.filter(F.arrays_zip(F.slice(t, i, width).alias("t"), F.slice(r, i, width).alias("r")), lambda x: x["t"].startswith("<")), lambda x: x["r"])
            one = lambda i, key, raw, own: F.struct(F.size(raws).alias("total"), i.alias("place"), key.alias("key"), raw.alias("raw"), own.alias("slots"))
            none = F.lit(None).cast("array<string>")
            plain = lambda x, i: one(i + 1, x["r"], x["r"], none)
            each = lambda x, i: F.when(x["r"] == x["t"], F.array(plain(x, i))).otherwise(F.array(one(i + 1, x["t"], x["r"], slots(i + 1)), plain(x, i)))
            return F.flatten(F.transform(F.arrays_zip(raws.alias("r"), temps.alias("t")), each))

        return F.concat(*[of_width(F.get(rh, F.lit(at)), F.get(th, F.lit(at)), width) for at, width in enumerate(widths)])

    hashed = lambda r, t: let(_hashes(r, widths, suits), lambda rh: let(_hashes(t, widths, suits), lambda th: windows(r, t, rh, th)))
    made = let(marked_words(text), lambda words: let(F.transform(words, bare), lambda r: _template(words, lambda t: hashed(r, t))))
    return rows.select(*keys, F.explode(made).alias("w")).select(*keys, "w.*")


def matches(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, least: float = 0.5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, item_id, n_windows, n_matched, n_exact, coverage)`` of documents that hold a benchmark item.

    ``n_matched`` counts the item's windows found in the document. Where the item is laid upon the text, each of its slot
    values must stand for one value of the text; where that fails, only windows with the item's own values count.
    ``n_exact`` counts windows with the item's own words; a pair is reported at a ``coverage`` of the item's windows of
    ``least`` or more. An item shorter than a window is one window, and matches where its words stand. Of several texts
    under one item_id the best covered one counts. Null and empty texts and items match nothing; repeated rows count once;
    rows with a null id are left out.
    """
    items = benchmark.where(F.col("item_id").isNotNull() & F.col("text").isNotNull()).select("item_id", "text").distinct().select("item_id", F.xxhash64("text").alias("variant"), "text")
    sizes = items.select(F.size(marked_words(F.col("text"))).alias("n"))
    short = [r["n"] for r in sizes.where((F.col("n") > 0) & (F.col("n") < window)).distinct().orderBy("n").collect()]  # fewer widths than a window has words
    widths = [*short, window]
    whole = lambda n, width: (n == width) if width < window else (n >= width)
    wanted = materialize(_windows(items, ["item_id", "variant"], F.col("text"), widths, whole).select("item_id", "variant", "total", F.col("place").alias("item_place"), "key", F.col("raw").alias("item_raw"), F.col("slots").alias("item_slots")), "items")
    fits = wanted.df.count() <= BROADCAST_WINDOWS
    wanted = F.broadcast(wanted.df) if fits else wanted.df
    known = wanted.select("key").distinct()
    filled = lambda c: F.coalesce(c, F.array().cast("array<string>"))
    texts = docs.where(F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    # First which documents have a window of the benchmark at all; only these are laid upon the items.
    touched = materialize(_keys(texts, ["doc_id"], F.col("text"), widths, _long_enough).join(F.broadcast(known) if fits else known, "key", "left_semi").select("doc_id").distinct(), "touched")
    ids = F.broadcast(touched.df) if touched.df.count() <= BROADCAST_WINDOWS else touched.df
    texts = texts.join(ids, "doc_id", "left_semi")
    met = (
        _windows(texts, ["doc_id"], F.col("text"), widths, _long_enough).select("doc_id", "place", "key", "raw", "slots").join(wanted, "key")
        .select("doc_id", "item_id", "variant", "item_place", "total", (F.col("place") - F.col("item_place")).alias("shift"), (F.col("raw") == F.col("item_raw")).cast("int").alias("exact"),
                F.arrays_zip(filled(F.col("item_slots")).alias("i"), filled(F.col("slots")).alias("d")).alias("pairs"))
    )
    # One group for each place a text and an item are laid upon each other: at most the item's windows.
    item = ["doc_id", "item_id", "variant"]
    laid = met.groupBy(*item, "shift").agg(F.max("total").alias("total"), F.collect_set(F.struct("item_place", "exact")).alias("windows"), F.array_distinct(F.flatten(F.collect_set("pairs"))).alias("pairs"))
    laid = laid.withColumn("consistent", F.size(F.array_distinct(F.transform("pairs", lambda x: x["i"]))) == F.size("pairs"))
    counted = laid.select(*item, "total", "consistent", F.explode("windows").alias("w")).where("consistent or w.exact = 1")
    once = counted.groupBy(*item, "w.item_place").agg(F.max("total").alias("total"), F.max("w.exact").alias("exact"))
    found = once.groupBy(*item).agg(F.max("total").cast("long").alias("n_windows"), F.count(F.lit(1)).alias("n_matched"), F.sum("exact").alias("n_exact"))
    covered = found.withColumn("coverage", F.col("n_matched") / F.col("n_windows")).where(F.col("coverage") >= least)
    best = covered.groupBy("doc_id", "item_id").agg(F.max(F.struct("coverage", "n_exact", "n_matched", "n_windows")).alias("b"))
    return best.select("doc_id", "item_id", "b.n_windows", "b.n_matched", "b.n_exact", "b.coverage")


def without_leaks(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, least: float = 0.5) -> DataFrame:
    """The documents that hold no benchmark item, all columns as they were; rows with a null id are kept."""
    leaked = matches(docs, benchmark, window, least).select("doc_id").distinct()
    return docs.join(leaked, "doc_id", "left_anti").select(*docs.columns)
