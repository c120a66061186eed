"""Benchmark decontamination by spaced seeds.

Fixed masks pick token positions and ignore the others. A seed is the hash of the
tokens that a mask picks at a place; every mask begins with three kept positions, whose
hash is tried first, so that most places cost one hash. Where a document's seed is one
of a benchmark item's, the two are laid over each other at that shift and at the few
next to it, and equal tokens are counted: a changed token costs no more than itself, and
neither does one put in or left out. A shift counts if three neighbouring tokens agree at
it; of the shifts that lie no further apart than the tokens an item may lose, each item
token and each document token counts once, and the best such span of shifts is taken.

Items of fewer than SHORT tokens leave masks too few places. They are cut into one
segment more than the tokens they may lose, and the first three tokens of each segment
are their seeds: one segment at least is whole, so none is missed from eight tokens on.
Longer items are found by chance of four masks at every place: with a fifth of all tokens
changed at random, all of 200 items of 30 tokens were (tests measure it).

While the benchmark has at most SET_LIMIT seeds, places of documents are tried against
tables of bits in which each seed has set three; they go into the plan as one value, for
the driver copies and prints a list of all seeds at every step of planning. What passes
by chance falls away in the join on seeds that follows. Beyond the limit all places are
joined. Only DataFrame functions are used.

Defined results: null texts and items have no tokens; items with fewer than three
tokens take no part; rows are told apart by id and text, so null ids and repeated ids are
each held; rows that repeat both give the same single result; an empty benchmark
contaminates nothing; texts of any length are read whole.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from pairmatch.llm.common import stored

# 1 keeps a token, 0 ignores it.
MASKS = ("111011011", "1110010111", "11101001101", "111100111")
ANCHOR = 3
SET_LIMIT = 60_000
BITS, SLICES = 1 << 20, (0, 20, 40)  # bits of a table at most; the parts of a hash that set one each
SHARE = 0.8
SHORT = 24


def tokens(text: Column) -> Column:
    """Runs of letters and digits in lower case."""
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+"), lambda x: x != "")


def _picked(mask: str, at: str, t: str = "t") -> str:
    return ", ".join(f"{t}[{at} + {i}]" for i, c in enumerate(mask) if c == "1")


def _anchor(at: str) -> str:
    return f"xxhash64({_picked('1' * ANCHOR, at)})"


def _seed(m: int, at: str) -> str:
    return f"xxhash64({m}, {_picked(MASKS[m], at)})"


def _fits(m: int, at: str) -> str:
    return f"{at} + {len(MASKS[m])} <= size(t)"


def _items(bench: DataFrame, share: float) -> DataFrame:
    """item_id, ih (names an item, as ids may be null or repeat), t, lost (tokens it may lose)."""
    one = bench.select(F.col("item_id").cast("long").alias("item_id"), tokens(F.col("text")).alias("t")).where(F.size("t") >= ANCHOR).distinct()
    lost = F.expr(f"int(size(t) - ceil(size(t) * {round(share * 1000)} / 1000))")
    return one.select("item_id", F.xxhash64("item_id", F.col("item_id").isNull(), "t").alias("ih"), "t", lost.alias("lost"))


def _places(rows: DataFrame, keep: list[str]) -> DataFrame:
    return rows.select(*keep, F.expr(f"explode_outer(if(size(t) >= {ANCHOR}, sequence(0, size(t) - {ANCHOR}), array()))").alias("q"), "t").where("q is not null")


def _item_seeds(items: DataFrame) -> DataFrame:
    """ih, q, m, seed; short items have the first tokens of their segments, as mask -1."""
    each = ", ".join(f"if({_fits(m, 'q')}, {_seed(m, 'q')}, null)" for m in range(len(MASKS)))
    seeds = _places(items, ["ih"]).select("ih", "q", F.expr(f"posexplode_outer(array({each}))").alias("m", "seed")).where("seed is not null")
    cuts = f"transform(sequence(0, lost), i -> least(int(i * size(t) div (lost + 1)), size(t) - {ANCHOR}))"
    short = items.where(F.size("t") < SHORT).select("ih", F.explode_outer(F.expr(cuts)).alias("q"), "t").select("ih", "q", F.lit(-1).alias("m"), F.expr(_anchor("q")).alias("seed"))
    return seeds.unionByName(short).distinct()


def _bits(hashes) -> tuple[str, int]:
    """A table with 16 bits a hash or more, up to BITS, in which each hash sets three: as text, an array of longs; and its bits."""
    hashes, size = list(hashes), 64
    while size < min(16 * len(hashes), BITS):
        size *= 2
    words = [0] * (size // 64)
    for h in hashes:
        for s in SLICES:
            at = ((h % (1 << 64)) >> s) % size
            words[at // 64] |= 1 << at % 64
    return f"cast(split('{','.join(str(w - (1 << 64) if w >> 63 else w) for w in words)}', ',') as array<bigint>)", size


def _held(hash_: str, table: str, size: int) -> str:
    each = [f"(shiftright(get({table}, int(shiftright(x_, {s + 6}) & {size // 64 - 1}L)), int(shiftright(x_, {s}) & 63L)) & 1L) = 1L" for s in SLICES]
    return f"exists(array({hash_}), x_ -> {' and '.join(each)})"


def _doc_seeds(docs: DataFrame, anchors: set[int] | None, seeds: set[int] | None) -> DataFrame:
    """Documents' places and seeds; with sets, those that the benchmark has, and hardly any others, tokens kept."""
    each = ", ".join([f"if({_fits(m, 'q')}, {_seed(m, 'q')}, null)" for m in range(len(MASKS))] + [_anchor("q")])
    of_place = F.expr(f"explode_outer(filter(array({each}), s -> s is not null))").alias("seed")
    if anchors is None:
        return _places(docs, ["doc_id", "th"]).select("doc_id", "th", "q", of_place).where("seed is not null")
    (a, a_size), (b, b_size) = _bits(anchors), _bits(seeds)
    some = " or ".join([f"({_fits(m, 'i')} and {_held(_seed(m, 'i'), 'b_.s', b_size)})" for m in range(len(MASKS))] + [_held(_anchor("i"), "b_.s", b_size)])
    # outer explodes and no condition on a computed column: else the optimizer puts size(column) > 0,
    # with the column's whole expression inside the lambda, below the projection
    hit = f"if(size(t) >= {ANCHOR}, filter(sequence(0, size(t) - {ANCHOR}), i -> {_held(_anchor('i'), 'b_.a', a_size)} and ({some})), array())"
    held = docs.withColumn("at", F.expr(f"transform(array(named_struct('a', {a}, 's', {b})), b_ -> {hit})[0]"))
    return held.select("doc_id", "th", "t", F.explode_outer("at").alias("q")).where("q is not null").select("doc_id", "th", "t", "q", of_place).where("seed is not null")


def laid_over(t: str, b: str, shift: str, lost: str) -> Column:
    """start and matched of the best span of shifts around one, null where no three neighbouring tokens agree."""
    same = lambda s, j: f"({s} + {j} >= 0 and get({t}, {s} + {j}) <=> {b}[{j}])"
    run = " and ".join(same("s", f"(j + {i})") for i in range(ANCHOR))
    at = f"filter(sequence({shift} - {lost}, {shift} + {lost}), s -> exists(sequence(0, size({b}) - {ANCHOR}), j -> {run}))"
    pairs = f"flatten(transform(filter(ok, r -> r between s and s + {lost}), r -> transform(filter(sequence(0, size({b}) - 1), j -> {same('r', 'j')}), j -> named_struct('j', j, 'p', r + j))))"
    spans = f"transform(ok, s -> transform(array({pairs}), x -> named_struct('matched', least(size(array_distinct(x.j)), size(array_distinct(x.p))), 'first', -s))[0])"
    return F.expr(f"transform(array({at}), ok -> if(size(ok) = 0, null, array_max({spans})))[0]")


def overlaps(docs: DataFrame, bench: DataFrame, share: float = SHARE, set_limit: int = SET_LIMIT) -> DataFrame:
    """doc_id, text_hash, item_id, start (token), matched, item_tokens of each contaminated document and item."""
    items = stored(_items(bench, share), "bench-items")
    seeds = stored(_item_seeds(items), "bench-seeds")
    d = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("th"), tokens(F.col("text")).alias("t"))
    anchored = _places(items, ["ih"]).select(F.expr(_anchor("q")).alias("anchor")).distinct()
    few = seeds.select("seed").distinct().limit(set_limit + 1).count() <= set_limit and anchored.limit(set_limit + 1).count() <= set_limit
    if few:
        known = {r[0] for r in seeds.select("seed").distinct().collect()}  # at most set_limit
        anchors = {r[0] for r in anchored.collect()}  # at most set_limit
        found = _doc_seeds(d, anchors, known).join(seeds.select("ih", "seed", F.col("q").alias("at")), "seed")
        met = found.select("doc_id", "th", "t", "ih", (F.col("q") - F.col("at")).alias("shift"))
    else:
        found = _doc_seeds(d, None, None).join(seeds.select("ih", "seed", F.col("q").alias("at")), "seed")
        shifts = found.select("doc_id", "th", "ih", (F.col("q") - F.col("at")).alias("shift")).distinct()
        met = shifts.join(d.dropDuplicates(["doc_id", "th"]).withColumnRenamed("doc_id", "own"), ["th"]).where(F.col("own").eqNullSafe(F.col("doc_id"))).drop("own")
    # of the document only the tokens that the item can be laid over go along
    near = met.join(items.withColumnRenamed("t", "b"), "ih").withColumn("from", F.greatest(F.col("shift") - F.col("lost"), F.lit(0)))
    cut = near.select("doc_id", "th", "item_id", "ih", "b", "lost", "shift", "from", F.expr("slice(t, from + 1, greatest(shift - from + size(b) + lost, 1))").alias("t"))
    cut = cut.dropDuplicates(["doc_id", "th", "ih", "shift"])
    best = F.explode_outer(F.array(laid_over("t", "b", "(shift - from)", "lost")))
    one = cut.select("doc_id", "th", "item_id", "ih", F.size("b").alias("item_tokens"), "from", best.alias("best")).where("best is not null").select(
        "doc_id", "th", "item_id", "ih", "item_tokens", F.struct(F.col("best.matched").alias("matched"), (F.col("best.first") - F.col("from")).alias("first")).alias("best")
    ).groupBy("doc_id", "th", "item_id", "ih", "item_tokens").agg(F.max("best").alias("best"))
    enough = F.col("best.matched") * 1000 >= F.col("item_tokens") * round(share * 1000)
    return one.where(enough).select("doc_id", F.col("th").alias("text_hash"), "item_id", F.greatest(-F.col("best.first"), F.lit(0)).cast("int").alias("start"), F.col("best.matched").alias("matched"), "item_tokens")


def clean_of(docs: DataFrame, bench: DataFrame, share: float = SHARE) -> DataFrame:
    """The rows of docs that hold no benchmark item, all columns."""
    leaks = stored(overlaps(docs, bench, share).select(F.col("text_hash").alias("th")).distinct(), "leaks")
    # the row goes along whole, so that none of its names can clash
    held = docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("row"), F.xxhash64(F.coalesce(docs["text"], F.lit(""))).alias("th"))
    return held.join(leaks, "th", "left_anti").select("row.*")
