"""Mixing sources to target weights, with DataFrame functions only.

Every source's words form one stream (its documents in a fixed order), cut into blocks of `block` words. The output is
shards of `shard_blocks` slots. Each shard draws its sources by multinomial sampling: slot j of n takes the source in
whose part of the line a pseudorandom point of the j-th n-th falls (stratified points: any point of the line is equally
likely, and a shard's count of a source is within one slot of its share at either end of the part). The i-th slot of a
source maps through that source's permutation of its pass to a block; slots and blocks are then joined by (source, block).

Targets: sources by code point, null last, weigh 1, 2, 3, repeating, and share all words; no target exceeds `most`
times its source's size, and the excess is shared again by weight (a water level over sources sorted by limit/weight).
A source is drawn in proportion to its target in blocks, so that the words taken come near the target: within one slot
for each shard and two blocks more. Slots drawn beyond `most` passes of a source take nothing. `block` is 4 unless given,
whatever the size of the table (`block_of` offers larger ones to other callers).

Every slot is drawn (`_runs` counts a shard's slots of each source; these follow each other, as points rise from slot to
slot) and sent to its block (`_dealt`). Uses of neighbouring blocks are kept together, some bits for each, so that slots
meet the documents' words in a row for each cell of blocks and not in one for each block (`cells_of`, `_pieces`).

Order and skew: documents are dealt to `spread` buckets of each source by doc_id, and the running sums are taken inside
a bucket, then over buckets, so that a source with a third of all rows is no single task's work. Only the table of
sources (one row each) is ordered in one task. Up to 2**36 slots.

Defined results: null text has size 0; a document of size 0 takes 0 words; a null doc_id sorts last; repeated rows are
documents of their own; a null source is a source; an empty table gives an empty result; other columns are ignored by
`mix` and kept by `mix_documents`.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from hitcodec.llm.common import SPACE, WORD, text_key, text_or_empty
from hitcodec.session import materialise

PRIME = 2147483647  # of the small generator that seeds the rounds
ROUNDS = 4
BLOCK = 4  # words
LINE = 40  # bits of the line of sources
TASK = 19  # bits of the number of slots that a task deals
WORD_BITS = 62  # of a cell of blocks


def _draw(seed: Column, turn: Column) -> Column:
    """A number below PRIME for a seed and a round; the same arithmetic works in any SQL engine."""
    first = (F.pmod(seed, F.lit(PRIME)) * 48271 + turn * 69621 + 11) % PRIME
    return ((first * 48271) % PRIME * 16807 + 97) % PRIME


def div(a: Column, b: Column | int) -> Column:
    """Integer division."""
    return F.call_function("div", a.cast("long"), (F.lit(b) if isinstance(b, int) else b).cast("long"))


def permuted(x: Column, n: Column, seed: Column) -> Column:
    """A pseudorandom bijection of [0, n): rounds of a rotation, then a mix of the largest power of two below n."""
    bits = F.length(F.bin(n)) - 1
    top = F.call_function("shiftleft", F.lit(1).cast("long"), bits)
    half = F.greatest(F.lit(1), (bits + 1).cast("int") - div(bits + 1, 2).cast("int"))

    def step(at: Column, turn: Column) -> Column:
        odd = (_draw(seed, turn) % (1 << 25)) * 2 + 1
        mixed = (at * odd).bitwiseAND(top - 1)
        mixed = mixed.bitwiseXOR(F.call_function("shiftright", mixed, half))
        return F.when(turn % 2 == 0, (at + _draw(seed, turn)) % n).when(at < top, mixed).otherwise(at)

    turns = F.array(*[F.lit(turn).cast("long") for turn in range(2 * ROUNDS)])
    return F.aggregate(turns, x.cast("long"), step)


def inverse_turns(n: Column, seed: Column) -> Column:
    """What `unpermuted` needs to undo `permuted(x, n, seed)`: n, the power of two below it, half of its bits, and from
    the last round to the first the halves (18 bits each) of the inverse of a round's factor and n less its rotation."""
    all_bits, low_bits = F.lit((1 << 36) - 1), F.lit((1 << 18) - 1)
    bits = F.length(F.bin(n)) - 1
    top = F.call_function("shiftleft", F.lit(1).cast("long"), bits)
    half = F.greatest(F.lit(1), (bits + 1).cast("int") - div(bits + 1, 2).cast("int"))

    def inverse(odd: Column) -> Column:
        def closer(x: Column, _: Column) -> Column:
            rest = (F.lit((1 << 36) + 2) - (odd * x).bitwiseAND(all_bits)).bitwiseAND(all_bits)
            high = F.shiftleft((x * F.shiftright(rest, 18)).bitwiseAND(low_bits), 18)
            return (x * rest.bitwiseAND(low_bits) + high).bitwiseAND(all_bits)

        return F.aggregate(F.array(*[F.lit(k) for k in range(5)]), odd, closer)  # 3 bits, then 6, 12, 24, 48, 96

    fields = [n.alias("n"), top.alias("top"), half.alias("half")]
    for k in range(ROUNDS):
        odd = (_draw(seed, F.lit(2 * k + 1)) % (1 << 25)) * 2 + 1
        whole = inverse(odd).bitwiseAND(top - 1)
        fields += [whole.bitwiseAND(low_bits).alias(f"lo{k}"), F.shiftright(whole, 18).alias(f"hi{k}"), (n - _draw(seed, F.lit(2 * k)) % n).alias(f"back{k}")]
    return F.struct(*fields)


def unpermuted(ys: Column, turns: Column) -> Column:
    """For an array of numbers, those that `permuted` takes to them; turns: of `inverse_turns`."""
    low_bits = F.lit((1 << 18) - 1)

    def undo(k: int):
        def step(y: Column) -> Column:
            held = y.bitwiseXOR(F.call_function("shiftright", y, turns["half"]))
            product = held * turns[f"lo{k}"] + F.shiftleft((held * turns[f"hi{k}"]).bitwiseAND(low_bits), 18)
            return (F.when(y < turns["top"], product.bitwiseAND(turns["top"] - 1)).otherwise(y) + turns[f"back{k}"]) % turns["n"]

        return step

    for k in reversed(range(ROUNDS)):
        ys = F.transform(ys, undo(k))
    return ys


def word_count(text: Column) -> Column:
    """Words of a text: each, with the white space before it, becomes one character; no array of words is made."""
    return F.length(F.rtrim(F.regexp_replace(text, rf"[\x20\x09-\x0D]*{WORD}", "x"), F.lit(SPACE))).cast("long")


def sized(docs: DataFrame, spread: int = 1024) -> DataFrame:
    """Slim rows: doc_id, tk (text key), src (a key that tells null), source, bucket, size."""
    bucket = F.pmod(F.pmod(F.coalesce("doc_id", F.lit(0)).cast("long"), F.lit(1000003)) * 40503, F.lit(spread)).cast("int")
    return docs.select(
        F.col("doc_id").cast("long").alias("doc_id"), text_key().alias("tk"),
        F.coalesce(F.concat(F.lit("="), "source"), F.lit("")).alias("src"), "source", bucket.alias("bucket"),
        word_count(text_or_empty()).alias("size"),
    )


def targets(sizes: DataFrame, most: int = 3) -> DataFrame:
    """A row for each source: src, rn, source_size, weight, target."""
    per = sizes.groupBy("src", "source").agg(F.sum("size").alias("source_size"))
    order = Window.orderBy(F.col("source").asc_nulls_last())
    per = per.withColumn("rn", F.row_number().over(order)).withColumn("weight", (F.col("rn") - 1) % 3 + 1)
    limit = F.col("source_size") * most
    by_limit = Window.orderBy((limit / F.col("weight")).asc(), F.col("rn"))
    before = by_limit.rowsBetween(Window.unboundedPreceding, -1)
    since = by_limit.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    every = Window.orderBy("rn").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    level = (F.sum("source_size").over(every) - F.coalesce(F.sum(limit).over(before), F.lit(0))) / F.sum("weight").over(since)
    per = per.withColumn("level", level).withColumn("full", limit <= F.col("level") * F.col("weight"))
    water = F.max(F.when(~F.col("full"), F.col("level"))).over(every)
    target = F.when(F.col("full"), limit.cast("double")).otherwise(F.least(F.col("weight") * water, limit.cast("double")))
    return per.select("src", "rn", "source_size", "weight", target.alias("target"))


def block_of(words: int) -> int:
    """Words in a block of which a table has about 2**20, for callers that want few slots of large tables."""
    block = 4
    while block < 1024 and block << 20 < words:
        block *= 2
    return block


def plan_sources(per: DataFrame, block: int) -> DataFrame:
    """Adds to each source its blocks, the draws it should get, and its part [low, high) of the line."""
    per = per.withColumn("blocks", div(F.col("source_size") + (block - 1), block))
    per = per.withColumn("draws", F.when(F.col("blocks") > 0, F.col("target") * F.col("blocks") / F.col("source_size")).otherwise(0.0))
    upto = Window.orderBy("rn").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    every = Window.orderBy("rn").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    share = F.coalesce(F.sum("draws").over(upto) / F.nullif(F.sum("draws").over(every), F.lit(0.0)), F.lit(0.0))
    per = per.withColumn("high", F.round(share * float(1 << LINE)).cast("long"))
    return per.withColumn("low", F.coalesce(F.lag("high").over(Window.orderBy("rn")), F.lit(0)))


def _point(slot: Column, seed: Column) -> Column:
    """A number below PRIME for a slot."""
    first = _draw(slot + seed, F.lit(5))
    return _draw(first.bitwiseXOR(F.shiftright(first, 13)), F.lit(7))


def slot_count(per: DataFrame) -> int:
    n = per.agg(F.coalesce(F.round(F.sum("draws")).cast("long"), F.lit(0))).first()[0]  # one number
    if n >= 1 << 36:
        raise ValueError("too many slots: take larger blocks")
    return n


def _tasks(n: int) -> int:
    return max(1, -(-n >> TASK))


def _runs(per: DataFrame, n: int, shard_blocks: int, seed: int) -> DataFrame:
    """The draw of every slot, counted: shard, rn, blocks, slots (that follow each other), first (their first place in the
    shard), before (slots of the source in the shards before)."""
    shift = max(0, LINE - (4 * per.count()).bit_length())  # some cells of the line for each source
    cells = F.sequence(F.shiftright("low", shift), F.shiftright(F.col("high") - 1, shift))
    spans = per.where("high > low").select("rn", "low", "high", "blocks", F.explode(cells).alias("cell"))
    shard, place = div(F.col("id"), shard_blocks), F.col("id") % shard_blocks
    size = F.least(F.lit(shard_blocks), F.lit(n) - shard * shard_blocks)
    made = per.sparkSession.range(0, n, 1, _tasks(n)).select(F.col("id").alias("at"), shard.alias("shard"), place.alias("j"), size.alias("size"))
    point = div(F.shiftleft("j", LINE) + F.shiftleft(_point(F.col("at"), F.lit(seed)), LINE - 31), F.col("size"))
    made = made.select("shard", "j", point.alias("point")).withColumn("cell", F.shiftright("point", shift))
    drawn = made.join(spans, "cell").where("point >= low and point < high")
    counts = drawn.groupBy("shard", "rn", "blocks").agg(F.count(F.lit(1)).alias("slots"), F.min("j").alias("first"))
    before = Window.partitionBy("rn").orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    return counts.withColumn("before", F.coalesce(F.sum("slots").over(before), F.lit(0)))


def _dealt(per: DataFrame, n: int, shard_blocks: int, seed: int, most: int) -> DataFrame:
    """A row for each slot of the mix that takes a block: shard, rn, j (place in the shard's draw), turn (pass), block.

    Steps as in `permuted`; what only depends on source and pass is made once for all slots of a run."""
    runs = _runs(per, n, shard_blocks, seed).where(F.col("before") < F.col("blocks") * most).repartition(_tasks(n), "shard", "rn")
    last = F.least(F.lit(most - 1).cast("long"), div(F.col("before") + F.col("slots") - 1, F.col("blocks")))
    runs = runs.withColumn("turn", F.explode(F.sequence(div(F.col("before"), F.col("blocks")), last)))
    bits, key = F.length(F.bin("blocks")) - 1, F.col("rn") * 7919 + F.col("turn") * 104729 + seed
    fields = {"top": F.call_function("shiftleft", F.lit(1).cast("long"), bits), "half": F.greatest(F.lit(1), (bits + 1).cast("int") - div(bits + 1, 2).cast("int"))}
    for k in range(ROUNDS):
        fields |= {f"add{k}": _draw(key, F.lit(2 * k)), f"odd{k}": (_draw(key, F.lit(2 * k + 1)) % (1 << 25)) * 2 + 1}
    fields["from"] = F.greatest(F.col("before"), F.col("turn") * F.col("blocks"))
    fields["to"] = F.least(F.col("before") + F.col("slots"), (F.col("turn") + 1) * F.col("blocks")) - 1
    each = runs.withColumns(fields).withColumn("i", F.explode(F.sequence("from", "to")))
    each = each.withColumns({"j": F.col("i") - F.col("before") + F.col("first"), "x": F.col("i") - F.col("turn") * F.col("blocks")})
    for k in range(ROUNDS):
        each = each.withColumn("x", (F.col("x") + F.col(f"add{k}")) % F.col("blocks"))
        each = each.withColumn("m", (F.col("x") * F.col(f"odd{k}")).bitwiseAND(F.col("top") - 1))
        each = each.withColumn("x", F.when(F.col("x") < F.col("top"), F.col("m").bitwiseXOR(F.call_function("shiftright", "m", "half"))).otherwise(F.col("x")))
    return each.select("shard", "rn", "j", "turn", F.col("x").alias("block"))


def slots(per: DataFrame, n: int, shard_blocks: int, seed: int, most: int) -> DataFrame:
    """A row for each slot of the mix that takes a block: slot (place in the output), shard, rn, turn (pass), block."""
    size = F.least(F.lit(shard_blocks), F.lit(n) - F.col("shard") * shard_blocks)
    out = F.col("shard") * shard_blocks + permuted(F.col("j"), size.cast("long"), F.col("shard") + seed)
    return _dealt(per, n, shard_blocks, seed, most).select(out.alias("slot"), "shard", "rn", "turn", "block")


def _cell(most: int) -> tuple[int, int]:
    """Bits that hold a block's uses, and blocks in a cell."""
    return most.bit_length(), WORD_BITS // most.bit_length()


def cells_of(drawn: DataFrame, most: int) -> DataFrame:
    """Slots joined by (source, block): rn, cell, held (the uses of the cell's blocks, from the lowest bits on)."""
    bits, width = _cell(most)
    one = F.call_function("shiftleft", F.lit(1).cast("long"), ((F.col("block") % width) * bits).cast("int"))
    return drawn.groupBy("rn", div(F.col("block"), width).alias("cell")).agg(F.sum(one).alias("held"))


def _uses_of(held: Column, place: Column, most: int) -> Column:
    """The uses of one block of a cell, by its place in it."""
    bits, _ = _cell(most)
    return F.call_function("shiftright", held, (place * bits).cast("int")).bitwiseAND(F.lit((1 << bits) - 1).cast("long"))


def _uses_in(held: Column, most: int) -> Column:
    """The uses of all blocks of a cell."""
    bits, width = _cell(most)
    planes = [sum(1 << (bits * k + p) for k in range(width)) for p in range(bits)]
    return sum((F.bit_count(held.bitwiseAND(F.lit(plane).cast("long"))).cast("long") * (1 << p) for p, plane in enumerate(planes)), F.lit(0).cast("long"))


def shard_counts(drawn: DataFrame) -> DataFrame:
    """The draw of each shard: how many of its slots each source has."""
    return drawn.groupBy("shard", "rn").agg(F.count(F.lit(1)).alias("slots"))


def _streams(sizes: DataFrame, per: DataFrame) -> DataFrame:
    """Each document's place in its source's stream, with its source's row of the plan."""
    inside = Window.partitionBy("src", "bucket").orderBy(F.col("doc_id").asc_nulls_last(), "tk", "size").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    across = Window.partitionBy("src").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    sums = sizes.groupBy("src", "bucket").agg(F.sum("size").alias("in_bucket"))
    sums = sums.select("src", "bucket", F.coalesce(F.sum("in_bucket").over(across), F.lit(0)).alias("before")).join(per, "src")
    placed = sizes.withColumn("upto", F.sum("size").over(inside)).join(sums, ["src", "bucket"])
    return placed.withColumn("at", F.col("before") + F.col("upto") - F.col("size"))


def _pieces(placed: DataFrame, cells: DataFrame, block: int, most: int) -> DataFrame:
    """A row for each cell that a document has words in: the document's columns, low and high (its blocks), cell, held."""
    _, width = _cell(most)
    some = placed.where("size > 0").withColumns({"low": div(F.col("at"), block), "high": div(F.col("at") + F.col("size") - 1, block)})
    some = some.withColumn("cell", F.explode(F.sequence(div(F.col("low"), width), div(F.col("high"), width))))
    return some.join(cells, ["rn", "cell"], "left").withColumn("held", F.coalesce("held", F.lit(0).cast("long")))


def _plan(docs: DataFrame, block: int, shard_blocks: int, seed: int, most: int, spread: int):
    """(sizes, sources, slots, cells of blocks with their uses)"""
    sizes = materialise(sized(docs, spread), "mix-sizes")
    per = materialise(plan_sources(targets(sizes, most), block), "mix-sources")
    drawn = slots(per, slot_count(per), shard_blocks, seed, most)
    return sizes, per, drawn, materialise(cells_of(drawn, most), "mix-uses")


def mix_plan(docs: DataFrame, block: int = BLOCK, shard_blocks: int = 4096, seed: int = 1, most: int = 3, spread: int = 1024):
    """(placed documents, uses of blocks, slots, words in a block): what both forms of the result derive from."""
    sizes, per, drawn, cells = _plan(docs, block, shard_blocks, seed, most, spread)
    _, width = _cell(most)
    uses = cells.withColumn("place", F.explode(F.sequence(F.lit(0), F.lit(width - 1))))
    uses = uses.select("rn", (F.col("cell") * width + F.col("place")).alias("block"), _uses_of(F.col("held"), F.col("place"), most).alias("uses"))
    return _streams(sizes, per), uses.where("uses > 0"), drawn, block


def mix(docs: DataFrame, block: int = BLOCK, shard_blocks: int = 4096, seed: int = 1, most: int = 3, spread: int = 1024) -> DataFrame:
    """What the mix takes of each document: doc_id, size, source_size, target, taken, source.

    docs: doc_id, text, source. Options: block (words in a block), shard_blocks, seed, most, spread.
    """
    sizes, per, _, cells = _plan(docs, block, shard_blocks, seed, most, spread)
    bits, width = _cell(most)
    pieces = _pieces(_streams(sizes, per), cells, block, most)
    low, high = F.greatest("low", F.col("cell") * width) % width, F.least("high", F.col("cell") * width + (width - 1)) % width
    own = F.call_function("shiftright", "held", (low * bits).cast("int"))
    own = own.bitwiseAND(F.call_function("shiftleft", F.lit(1).cast("long"), ((high - low + 1) * bits).cast("int")) - 1)
    # blocks are whole but for the first and the last one of a document
    lead, end = F.col("at") % block, F.pmod(-(F.col("at") + F.col("size")), F.lit(block))
    ends = [(F.col("low"), lead), (F.col("high"), end)]
    out = sum((F.when(div(b, width) == F.col("cell"), _uses_of(F.col("held"), b % width, most) * left).otherwise(0) for b, left in ends), F.lit(0).cast("long"))
    keep = ["doc_id", "size", "source_size", "target"]
    taken = pieces.groupBy("rn", "at", *keep, "source").agg(F.sum(_uses_in(own, most) * block - out).alias("taken"))
    none = sizes.where("size = 0").join(per.select("src", "source_size", "target"), "src")
    return taken.select(*keep, "taken", "source").unionByName(none.select(*keep, F.lit(0).cast("long").alias("taken"), "source"))


def mix_documents(docs: DataFrame, block: int = BLOCK, shard_blocks: int = 4096, seed: int = 1, most: int = 3, spread: int = 1024) -> DataFrame:
    """The mixed documents, with the columns of docs: a row for each pass that takes all of a source's blocks, and one for
    the words of the last pass, which takes some.

    Whole passes leave the text as it is; the last pass joins the words it takes by single spaces. n_chars, if there is
    such a column, counts the new text. Documents of which the mix takes nothing go; those of size 0 go too.
    """
    sizes, per, _, cells = _plan(docs, block, shard_blocks, seed, most, spread)
    _, width = _cell(most)
    drawn = cells.groupBy("rn").agg(F.sum(_uses_in(F.col("held"), most)).alias("drawn"))  # a row for each source
    passes = div(F.col("drawn"), F.greatest("blocks", F.lit(1)))
    placed = _streams(sizes, per.join(drawn, "rn").withColumn("passes", passes))
    keep = ["doc_id", "tk", "src", "size", "passes", "low", "high"]
    decided = _pieces(placed, cells, block, most).groupBy("rn", "at", *keep).agg(F.array_sort(F.collect_list(F.struct("cell", "held"))).alias("held"))
    held = lambda k: F.get("held", (div(k, width) - div(F.col("low"), width)).cast("int"))["held"]
    above = lambda k: _uses_of(held(F.col("low") + k), (F.col("low") + k) % width, most) > F.col("passes")
    taken = F.filter(F.sequence(F.lit(0), (F.col("high") - F.col("low")).cast("int")), above)  # from a document's first block
    decided = decided.withColumn("taken", taken).where("passes > 0 or size(taken) > 0").withColumn("lead", (F.col("at") % block).cast("int"))
    # rows meet what was decided on them in one exchange of the texts; repeated rows are told apart by numbers
    key = lambda doc_id, tk, src: [F.coalesce(doc_id, F.lit(0)).alias("_d"), doc_id.isNull().alias("_z"), tk.alias("_t"), src.alias("_s")]
    rows = docs.select(F.struct("*").alias("row"), *key(F.col("doc_id").cast("long"), text_key(), F.coalesce(F.concat(F.lit("="), "source"), F.lit(""))), F.lit(None).cast("long").alias("at"))
    decided = decided.select(*key(F.col("doc_id"), F.col("tk"), F.col("src")), "at", F.struct("passes", "taken", "lead").alias("of"))
    both = rows.unionByName(decided, allowMissingColumns=True).repartition("_d", "_z", "_t", "_s").withColumn("_row", F.col("row").isNotNull())
    both = both.withColumn("_n", F.row_number().over(Window.partitionBy("_d", "_z", "_t", "_s", "_row").orderBy("at")))
    pair = Window.partitionBy("_d", "_z", "_t", "_s", "_n").orderBy("_row").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    both = both.withColumn("of", F.first("of", ignorenulls=True).over(pair)).where("row is not null and of is not null").select("row", "of.*")
    turns = F.concat(F.when(F.col("passes") > 0, F.array_repeat(F.lit(True), F.col("passes").cast("int"))).otherwise(F.array().cast("array<boolean>")), F.when(F.size("taken") > 0, F.array(F.lit(False))).otherwise(F.array().cast("array<boolean>")))
    both = both.select("row", "taken", "lead", F.explode(turns).alias("whole"))
    text = F.col("row.text")
    words = F.regexp_extract_all(text, F.lit(WORD), F.lit(0))
    # an array of one, so that a text is cut into words once and not for each of its slices
    start = lambda k: k * block - F.col("lead")
    cut = lambda held, k: F.slice(held, F.greatest(start(k), F.lit(0)) + 1, F.least(F.lit(block), start(k) + block))
    part = F.transform(F.array(words), lambda held: F.array_join(F.flatten(F.transform("taken", lambda k: cut(held, k))), " "))
    both = both.withColumn("new", F.when(F.col("whole"), text).otherwise(F.get(part, F.lit(0))))
    out = F.col("row").withField("text", F.col("new"))
    if "n_chars" in docs.columns:
        out = out.withField("n_chars", F.length("new").cast(docs.schema["n_chars"].dataType))
    return both.select(out.alias("row")).select("row.*")
