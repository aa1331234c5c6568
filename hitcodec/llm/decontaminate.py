"""Benchmark decontamination by templates, with DataFrame functions only.

Texts become token sequences in which numbers, names (capitalised words) and units (after a number) are replaced by typed
placeholders. A capitalised word at the start of a text or sentence may be a name or not: the benchmark's windows are
looked for under every choice, the documents' with all such words as names and with none, so that neither what stands
before a pasted item nor other names at its sentence starts hide it. Windows of `window` template tokens are hashed and
hash-joined with those of the benchmark, so that a question with other numbers or names still meets its source. Matches are grouped by alignment; a
match counts if its slots are consistent: every filler of the item stands for one filler in the document throughout
(windows with words that only may be names are left out where these clash; sure slots that clash rule out the match).
A document is contaminated by an item if at least `least` windows of the item match (eight tokens a window and six
windows: 13 tokens in a row), or all of a shorter item's.

The benchmark's windows are broadcast only if their counted bytes are at most `broadcast_bytes`; beyond that both sides
are shuffled by hash, and the texts with partners are joined again for what stands in their windows. Items of equal template whose slots hold equal fillers at the same places (so that a document is
consistent with all or none of them) are one item, the smallest item_id, with their number.

Defined results: null and empty texts match nothing; items of fewer than `window` tokens are looked for as one window of
their full width, and left out below `short` tokens; windows with fewer than half literal tokens are looked for word
for word only, without templates; an item is held if `least` of its windows match, or of those with literals enough all
there are (if there are any); a null doc_id is kept as it is; repeated rows are told apart by text only, equal rows give one result;
an empty table gives an empty result; other columns are ignored by `contaminated` and kept by `decontaminate`.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hitcodec.llm.common import text_key, text_or_empty
from hitcodec.session import materialise

NUMBER, NAME, UNIT, MAYBE = "", "", "", ""
# Units that follow a number.
UNITS = (
    "mm cm dm m km in inch inches ft foot feet yd yards mi mile miles mg g kg t lb lbs oz ounces tons ml cl dl l liter "
    "liters litre litres gallons s sec seconds min minutes h hr hours hour day days week weeks month months year years "
    "percent pct usd eur dollars euros cents pounds hz khz mhz ghz kb mb gb tb w kw mw v kv a j kj k c f degrees"
).split()
TOKEN = rf"[{NUMBER}{NAME}{UNIT}{MAYBE}]|\d+(?:[.,]\d+)*|[\p{{L}}\p{{M}}]+"
NAME_AT = rf"(?<=[\p{{Ll}}\p{{N}},;:)] )\p{{Lu}}[\p{{L}}\p{{M}}]*"
# Capitalised words elsewhere: at the start of a text or sentence, where they are names or words.
MAYBE_AT = r"(?<![\p{L}\p{M}\p{N}])\p{Lu}[\p{L}\p{M}]*"
NUMBER_AT = r"\d+(?:[.,]\d+)*"
UNIT_AT = rf"(?<={NUMBER} ?)(?i:{'|'.join(sorted(UNITS, key=lambda u: (-len(u), u)))})(?![\p{{L}}\p{{M}}])"


def template(text: Column) -> tuple[Column, Column]:
    """Template tokens and, token by token, what stands in the text. Whether a word that begins a sentence is a name is left open."""
    marked = F.regexp_replace(F.regexp_replace(text, NAME_AT, NAME), MAYBE_AT, MAYBE)
    marked = F.regexp_replace(F.regexp_replace(marked, NUMBER_AT, NUMBER), UNIT_AT, UNIT)
    return F.regexp_extract_all(F.lower(marked), F.lit(TOKEN), F.lit(0)), F.regexp_extract_all(F.lower(text), F.lit(TOKEN), F.lit(0))


def is_slot(token: Column) -> Column:
    return token.isin(NUMBER, NAME, UNIT)


def _slices(width: int, *names: str) -> list:
    """A function of a place (from 1) for each array: what stands there, `width` wide."""
    return [lambda i, n=n: F.slice(n, i, width) for n in names]


def _places(width: int) -> Column:
    count = F.size("tokens") - (width - 1)
    return F.when(count > 0, F.sequence(F.lit(1), F.greatest(count, F.lit(1)))).otherwise(F.array().cast("array<int>"))


def _marked(df: DataFrame, key: list[Column]) -> DataFrame:
    marked, raw = template(text_or_empty())
    return df.select(*key, marked.alias("marked"), raw.alias("raw"))


def _templates(df: DataFrame, key: list[Column]) -> DataFrame:
    """Both typings of texts: in `tokens` all capitalised words are names, in `words` those that begin a sentence stand for themselves."""
    words = F.zip_with("marked", "raw", lambda t, r: F.when(t == MAYBE, r).otherwise(t))
    return _marked(df, key).select("*", F.transform("marked", lambda t: F.when(t == MAYBE, NAME).otherwise(t)).alias("tokens"), words.alias("words")).drop("marked")


def _hash(width: int, token_hash) -> Column:
    """Hash of a window by its tokens' hashes, a function of the place in it."""
    return F.xxhash64(F.lit(width), *[token_hash(k) for k in range(width)])


def _windows(rows: DataFrame, widths: list[int], keep: list[str]) -> DataFrame:
    """The windows of documents, a row for each typing: keep, the text's marked and raw tokens, at (from 1), hash.

    Tokens are hashed once and windows take these hashes by place, so that no window has arrays of its own."""
    least = min(widths)
    places = F.when(F.size("raw") >= least, F.sequence(F.lit(0), F.size("raw") - least)).otherwise(F.array().cast("array<int>"))
    names = F.transform("marked", lambda t: F.xxhash64(F.when(t == MAYBE, NAME).otherwise(t)))
    rows = rows.select(*keep, "marked", "raw", names.alias("names"), F.transform("raw", lambda t: F.xxhash64(t)).alias("plain"))
    rows = rows.select("*", F.explode(places).alias("place"))
    at = lambda name, k: F.get(name, F.col("place") + k)
    maybe = lambda k: F.when(at("marked", k) == MAYBE, at("plain", k)).otherwise(at("names", k))
    typed = []
    for w in widths:
        rows = rows.withColumns({f"t{w}": _hash(w, lambda k: at("names", k)), f"r{w}": _hash(w, lambda k: at("plain", k))})
        # all names, words where a name is not sure, what stands there: one where nothing is a slot
        each = F.when(F.col(f"t{w}") == F.col(f"r{w}"), F.array(f"t{w}")).otherwise(F.array_distinct(F.array(F.col(f"t{w}"), _hash(w, maybe), F.col(f"r{w}"))))
        typed.append(each if w == least else F.when(F.size("raw") >= F.col("place") + w, each).otherwise(F.array().cast("array<long>")))
    return rows.select(*keep, "marked", "raw", (F.col("place") + 1).alias("at"), F.explode(F.concat(*typed) if len(typed) > 1 else typed[0]).alias("hash"))


def _held(rows: DataFrame, width: Column | int) -> DataFrame:
    """In place of the text's tokens what stands in the window: raw, and words, where names that are not sure stand for themselves."""
    marked, raw = F.slice("marked", F.col("at"), width), F.slice("raw", F.col("at"), width)
    words = F.zip_with(marked, raw, lambda t, r: F.when(t == MAYBE, r).otherwise(t))
    return rows.withColumns({"raw": raw, "words": words}).drop("marked")


def _typings(of: Column) -> Column:
    """All typings of a window: every choice between tokens and words, place by place."""
    choices = F.zip_with(of["tokens"], of["words"], lambda t, w: F.array_distinct(F.array(t, w)))
    none = F.array(F.array().cast("array<string>"))
    return F.aggregate(choices, none, lambda made, c: F.flatten(F.transform(made, lambda m: F.transform(c, lambda x: F.concat(m, F.array(x))))))


def benchmark_windows(benchmark: DataFrame, window: int = 8, short: int = 5) -> DataFrame:
    """Windows of distinct items, a row for each typing: item_id, copies, total (windows of the item), windows (those with literals enough), width, hash, item_at, heavy (too many slots), item_tokens, item_words, item_raw."""
    items = _templates(benchmark, [F.col("item_id").cast("long").alias("item_id")]).where(F.size("tokens") >= short)
    one = F.min_by(F.struct("tokens", "words", "raw"), F.coalesce("item_id", F.lit(0)))
    both = F.arrays_zip("tokens", "raw")
    pattern = F.transform(both, lambda x: F.array_position(both, x))  # which slots hold equal fillers
    items = items.withColumn("same", F.xxhash64("tokens", F.lit(0), "words", F.lit(0), pattern)).groupBy("same")
    items = items.agg(F.min("item_id").alias("item_id"), F.count(F.lit(1)).alias("copies"), one.alias("of")).select("item_id", "copies", "of.*")
    both = None
    for width in range(short, window + 1):  # an item below `window` is one window of its own full width
        rows = items.where(F.size("tokens") == width if width < window else F.size("tokens") >= window)
        tokens, words, raw = _slices(width, "tokens", "words", "raw")
        each = F.transform(_places(width), lambda i: F.struct(i.alias("at"), tokens(i).alias("tokens"), words(i).alias("words"), raw(i).alias("raw")))
        found = rows.select("item_id", "copies", F.lit(width).alias("width"), F.explode(each).alias("of"))
        both = found if both is None else both.unionByName(found)
    # what only the start of an item makes a slot is not counted
    start = F.when((F.col("of.at") == 1) & ~is_slot(F.col("of.words")[0]), 1).otherwise(0)
    slots = lambda v: F.size(F.filter(v, is_slot)) - F.when(is_slot(v[0]), start).otherwise(0)
    both = both.withColumn("heavy", F.size(F.filter("of.words", is_slot)) * 2 > F.col("width")).withColumn("typings", _typings(F.col("of")))
    both = both.withColumn("kept", F.filter("typings", lambda v: slots(v) * 2 <= F.col("width")))
    whole = F.size("kept") == F.size("typings")  # else copies of the text itself are looked for too
    both = both.withColumn("kept", F.when(whole, F.col("kept")).otherwise(F.array_union("kept", F.array("of.raw"))))
    count = both.groupBy(F.col("item_id").alias("_item"), F.col("width").alias("_width")).agg(F.count(F.lit(1)).alias("total"), F.count_if(~F.col("heavy")).alias("windows"))
    both = both.join(count, F.expr("item_id <=> _item and width = _width")).withColumn("typed", F.explode("kept"))
    hashes = [F.when(F.col("width") == w, _hash(w, lambda k: F.xxhash64(F.get("typed", F.lit(k))))) for w in range(short, window + 1)]
    return both.select("item_id", "copies", "total", "windows", "width", F.coalesce(*hashes).alias("hash"), F.col("of.at").alias("item_at"), "heavy", F.col("of.tokens").alias("item_tokens"), F.col("of.words").alias("item_words"), F.col("of.raw").alias("item_raw"))


def contaminated(docs: DataFrame, benchmark: DataFrame, window: int = 8, short: int = 5, least: int = 6, broadcast_bytes: int = 32 << 20) -> DataFrame:
    """A row for each document and item it holds: doc_id, tk (text key), item_id, copies (of the item), windows, matched, same (are all fillers the item's)."""
    known = materialise(benchmark_windows(benchmark, window, short), "benchmark-windows")
    held = F.length(F.to_json(F.struct("item_tokens", "item_words", "item_raw"))) * 4 + 400  # more than a row's bytes
    counts = {r["width"]: r["bytes"] for r in known.groupBy("width").agg(F.sum(held).alias("bytes")).collect()}  # a row for each width that occurs
    texts = _marked(docs, [F.col("doc_id").cast("long").alias("doc_id"), text_key().alias("tk")])
    found = _windows(texts, sorted(counts) or [window], ["doc_id", "tk"])
    if sum(counts.values()) <= broadcast_bytes:
        hits = _held(found.join(F.broadcast(known), "hash"), F.col("width"))
    else:  # the windows travel: only the hash finds partners, then each document's tokens are asked for
        pairs = found.drop("marked", "raw").join(known, "hash")
        texts = texts.select(F.col("doc_id").alias("_doc"), F.col("tk").alias("_tk"), "marked", "raw").dropDuplicates(["_doc", "_tk"])
        pairs = pairs.join(texts, F.col("doc_id").eqNullSafe(F.col("_doc")) & (F.col("tk") == F.col("_tk")))
        hits = _held(pairs, F.col("width"))
    # a document's window without slots holds the item's own words
    place = F.arrays_zip(F.col("item_tokens").alias("t"), F.col("item_words").alias("iw"), F.col("item_raw").alias("i"), F.coalesce("words", "item_raw").alias("dw"), F.coalesce("raw", "item_raw").alias("d"))
    slots = F.filter(place, lambda x: is_slot(x["t"]) | (x["i"] != x["d"]))
    fillers = F.transform(slots, lambda x: F.struct(x["t"].alias("kind"), x["i"].alias("item"), x["d"].alias("doc"), (is_slot(x["iw"]) & is_slot(x["dw"])).alias("sure")))
    of = ["doc_id", "tk", "item_id", "copies", "windows", "total"]
    hits = hits.select(*of, (F.col("at") - F.col("item_at")).alias("shift"), F.struct("item_at", "heavy", fillers.alias("pairs")).alias("hit"))
    runs = hits.groupBy(*of, "shift").agg(F.collect_set("hit").alias("hits"))
    runs = runs.withColumn("pairs", F.array_distinct(F.flatten("hits.pairs")))
    against = lambda p, q: (p["kind"] == q["kind"]) & (p["item"] == q["item"]) & (p["doc"] != q["doc"])
    runs = runs.withColumn("clash", F.filter("pairs", lambda p: F.exists("pairs", lambda q: against(p, q))))
    runs = runs.where(~F.exists("clash", lambda p: p["sure"] & F.exists("clash", lambda q: q["sure"] & against(p, q))))
    # words that only may be names prove nothing against an alignment: where they clash, their windows do not count
    runs = runs.withColumn("hits", F.filter("hits", lambda h: ~F.exists(h["pairs"], lambda p: ~p["sure"] & (p["item"] != p["doc"]) & F.array_contains("clash", p))))
    runs = runs.withColumn("kept", F.forall(F.flatten("hits.pairs"), lambda p: p["item"] == p["doc"])).withColumn("ats", F.transform("hits", lambda h: F.struct(h["item_at"].alias("at"), h["heavy"].alias("heavy"))))
    pairs = runs.where(F.size("ats") > 0).groupBy(*of).agg(F.array_distinct(F.flatten(F.collect_list("ats"))).alias("ats"), F.bool_and("kept").alias("same"))
    pairs = pairs.withColumn("light", F.size(F.filter("ats", lambda x: ~x["heavy"]))).withColumn("matched", F.size("ats"))
    enough = (F.col("windows") > 0) & (F.col("light") >= F.least(F.lit(least), F.col("windows"))) | (F.col("matched") >= F.least(F.lit(least), F.col("total")))
    return pairs.where(enough).select("doc_id", "tk", "item_id", "copies", F.col("total").alias("windows"), "matched", "same")


def decontaminate(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """The rows of docs, all columns, that hold no item."""
    bad = contaminated(docs, benchmark, **options).select(F.col("doc_id").alias("_bad_doc"), F.col("tk").alias("_bad_tk")).distinct()
    rows = docs.select(F.struct("*").alias("row"), F.col("doc_id").cast("long").alias("_d"), text_key().alias("_t"))
    return rows.join(bad, F.col("_d").eqNullSafe(F.col("_bad_doc")) & (F.col("_t") == F.col("_bad_tk")), "left_anti").select("row.*")
