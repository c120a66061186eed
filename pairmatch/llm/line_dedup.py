"""Duplicate lines, equal or within a few edits, by segment partition.

Lines are compared folded: lower case, runs of white space as one space, ends trimmed.
Equal lines of any length are found by hash. Near lines may differ by one edit for each
CHARS_AN_EDIT characters of the shorter one, and by EDITS at most. A line of length l that
may differ by e edits is cut into e + 1 segments, one of which any line within so many
edits has untouched, at a place that its length bounds. Each distinct line is indexed by (length, segment number,
segment) and probes, for each length from its own down to EDITS less, the few
substrings that can be that segment. What meets, and whose counts of common letters do
not rule it out, is verified by an edit distance computed along a band of 2 x EDITS + 1
diagonals held in the bits of one integer.

A line goes if an equal line, or one within EDITS edits, stands earlier by document id
and place. Only DataFrame functions are used; only lines that share a segment ever
meet, as hashes, and texts are fetched for those alone.

Defined results: folded lines shorter than `least_chars` never go, nor count as earlier
lines (the queries ask for ANY, which leaves out blank lines alone); null texts have no lines; rows that repeat id and text are one document; null ids
come before all others. Lines of any length take part whole. without_duplicate_lines
leaves an empty text where every line stands elsewhere.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from pairmatch.llm.common import stored

EDITS = 2
LEAST_CHARS = 30
ANY = 1
CHARS_AN_EDIT = 15
LETTERS = "etno"
RARER = "aisrhldcum"
OFTEN = 40
COPIES = 16
MOST_WORDS = 1 << 20  # of 64 bits: the bound of what is sent to all


def fold(line: Column) -> Column:
    """White space inside as one space, ends trimmed; few lines need the pattern run over them."""
    odd = F.lit(False)
    for x in ("  ", "\t", "\r", "\x0b", "\f"):
        odd = odd | F.contains(line, F.lit(x))
    return F.trim(F.when(odd, F.regexp_replace(line, r"\s+", " ")).otherwise(line))


def allowed(n: Column, edits: int) -> Column:
    """Edits by which a line may differ from one of n characters that is no longer."""
    return F.least(F.lit(edits), F.floor(n / CHARS_AN_EDIT).cast("int"))


def placed_lines(docs: DataFrame, least_chars: int = LEAST_CHARS) -> DataFrame:
    """doc (null id: the least long), th, line_no, norm, n, h, h2 of the lines that count."""
    doc = F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63)))
    each = docs.where(F.col("text").isNotNull()).select(doc.alias("doc"), F.xxhash64("text").alias("th"), F.posexplode_outer(F.split(F.lower("text"), "\n")).alias("line_no", "line"))
    # held, as the filter would be pushed below the folding with a copy of it
    each = _held(each, "norm", fold(F.col("line"))).drop("line")
    each = each.withColumn("n", F.length("norm")).where(F.col("n") >= least_chars)
    return each.withColumns({"h": F.xxhash64("norm"), "h2": F.xxhash64(F.lit(1), F.col("norm"))})


def lines(docs: DataFrame, least_chars: int = LEAST_CHARS, edits: int = EDITS) -> DataFrame:
    """The same without norm, but with sk, ix and pr: sketch, index and probe keys."""
    usual, all_keys = usual_keys(edits), segment_keys(edits)
    each = _held(placed_lines(docs, least_chars), "sk", sketch(F.col("norm")))
    # lambdas keep what is computed beside them out of whole-stage code, and so come last
    for name, keys in zip(("ix", "pr"), usual, strict=True):
        each = _held(each, name, keys)
    return each.withColumns({name: F.coalesce(name, keys) for name, keys in zip(("ix", "pr"), all_keys, strict=True)}).drop("norm")


def _places(e: int) -> tuple[list, list]:
    """(characters less, segment, shift) of the index and of the probes: substrings that can be an untouched segment of a line no longer."""
    index = [(0, i, 0) for i in range(e + 1)]
    probes = []
    for less in range(e + 1):
        for i in range(e + 1):
            low, high = max(-i, less - (e - i)), min(i, less + (e - i))
            probes += [(less, i, d) for d in range(low, high + 1) if less or d]
    return index, probes


def _keys(places: list, e: int, text: str) -> str:
    """SQL for the hashes of (length, segment, substring); the last segments are the longer ones."""
    k = e + 1
    spec = ", ".join(f"named_struct('less', {less}, 'i', {i}, 'd', {d})" for less, i, d in places)
    at = f"p.i * int((n - p.less) div {k}) + greatest(0, p.i - {k} + (n - p.less) % {k})"
    size = f"int((n - p.less) div {k}) + if({k} - p.i <= (n - p.less) % {k}, 1, 0)"
    return f"transform(array({spec}), p -> xxhash64(n - p.less, p.i, substr({text}, {at} + p.d + 1, {size})))"


def _plain_keys(places: list, e: int) -> str:
    """The same as _keys written out, over the bytes of norm: several times faster than a lambda, and longer code."""
    k = e + 1
    out = []
    for less, i, d in places:
        m = f"(n - {less})"
        at = "0" if i == 0 else f"int({m} div {k})" if i == 1 else f"{i} * int({m} div {k}) + greatest(0, {m} % {k} - {k - i})"
        size = f"int({m} div {k})" + (f" + int({m} % {k} >= {k - i})" if i else "")
        out.append(f"xxhash64({m}, {i}, substr(binary(norm), {at} + {d + 1}, {size}))")
    return f"array({', '.join(out)})"


def usual_keys(edits: int) -> tuple[Column, Column]:
    """The keys of segment_keys for single-byte lines that allow all edits, null for others."""
    if not edits:
        return F.lit(None).cast("array<long>"), F.lit(None).cast("array<long>")
    case = lambda which, over: F.expr(f"case when octet_length(norm) = n and n {over} {edits * CHARS_AN_EDIT} then {_plain_keys(_places(edits)[which], edits)} end")
    return case(0, ">="), case(1, ">")


def segment_keys(edits: int) -> tuple[Column, Column]:
    """Index and probe keys of columns norm and n; empty for lines that allow no edit."""
    out = []
    none = "cast(array() as array<bigint>)"
    for which in (0, 1):
        sides = []
        # bytes are cut in one step, characters are counted from the start each time; hashes are the same
        for text, when in (("binary(norm)", "octet_length(norm) = n"), ("norm", "true")):
            keys = [none] + [_keys(_places(e)[which], e, text) for e in range(1, edits + 1)]
            cases = f"when n >= {edits * CHARS_AN_EDIT} then {keys[edits]} " if not which else f"when n > {edits * CHARS_AN_EDIT} then {keys[edits]} "
            for e in range(edits, 0, -1):
                if which:  # of the lengths that allow e edits, the least still meets those of e - 1
                    cases += f"when n = {e * CHARS_AN_EDIT} then concat({keys[e]}, {keys[e - 1]}) "
                if e > 1:
                    cases += f"when n >= {(e - 1) * CHARS_AN_EDIT} then {keys[e - 1]} "
            sides.append(f"when {when} then case {cases} else {none} end")
        out.append(F.expr(f"case {' '.join(sides)} end"))
    return out[0], out[1]


def sketch(norm: Column, letters: str = LETTERS) -> Column:
    """Counts of up to eight letters, a byte each, modulo 128."""
    out = F.lit(0).cast("long")
    for i, c in enumerate(letters):
        n = F.octet_length(norm) - F.octet_length(F.replace(norm, F.lit(c), F.lit("")))
        out = out.bitwiseOR(F.shiftleft((n % 128).cast("long"), 8 * i))
    return out


def sketch_near(a: Column, b: Column, edits: Column, letters: str = LETTERS) -> Column:
    """Whether sketches allow so many edits: an edit puts in one letter at most, and takes out one at most."""
    more, less = F.lit(0), F.lit(0)
    for i in range(len(letters)):
        d = (F.shiftrightunsigned(a, 8 * i).bitwiseAND(127) - F.shiftrightunsigned(b, 8 * i).bitwiseAND(127) + 192) % 128 - 64
        more, less = more + F.greatest(d, F.lit(0)), less + F.greatest(-d, F.lit(0))
    return (more <= edits) & (less <= edits)


def letters_near(a: Column, b: Column, edits: Column) -> Column:
    """The same over RARER letters of the lines themselves."""
    more, less = F.lit(0), F.lit(0)
    count = lambda x, c: F.octet_length(x) - F.octet_length(F.replace(x, F.lit(c), F.lit("")))
    for c in RARER:
        d = count(a, c) - count(b, c)
        more, less = more + F.greatest(d, F.lit(0)), less + F.greatest(-d, F.lit(0))
    return (more <= edits) & (less <= edits)


def common_start(x: str, y: str) -> str:
    """SQL for the length of the common beginning of two different strings, by halving steps."""
    least = f"least(length({x}), length({y}))"
    steps = f"filter(transform(sequence(0, 30), i -> shiftleft(1, 30 - i)), k -> k <= {least})"
    return f"aggregate({steps}, 0, (p, k) -> if(p + k <= {least} and substr({x}, p + 1, k) = substr({y}, p + 1, k), p + k, p))"


def _held(df: DataFrame, name: str, value: Column) -> DataFrame:
    """A column computed once: the optimizer doesn't copy expressions through an outer explode."""
    return df.withColumn(name, F.explode_outer(F.array(value)))


def differing(pairs: DataFrame, a: str, b: str) -> DataFrame:
    """Adds x and y: what is left of columns a and b without their common ends, as characters, x no shorter."""
    longer = F.length(a) >= F.length(b)
    one = pairs.withColumns({"_x": F.when(longer, F.col(a)).otherwise(F.col(b)), "_y": F.when(longer, F.col(b)).otherwise(F.col(a))})
    one = _held(one, "_p", F.expr(common_start("_x", "_y")))
    one = _held(one, "_xy", F.expr("named_struct('x', substr(_x, _p + 1), 'y', substr(_y, _p + 1))"))
    one = _held(one, "_r", F.expr("named_struct('x', reverse(_xy.x), 'y', reverse(_xy.y))"))
    one = _held(one, "_s", F.expr(common_start("_r.x", "_r.y")))
    cut = lambda c: F.split(F.expr(f"substr(_xy.{c}, 1, length(_xy.{c}) - _s)"), "")
    empty = F.array().cast("array<string>")
    chars = lambda c: F.when(F.expr(f"length(_xy.{c}) = _s"), empty).otherwise(cut(c))
    return _held(_held(one, "x", chars("x")), "y", chars("y")).drop("_x", "_y", "_p", "_xy", "_r", "_s")


def within_edits(x: str, y: str, edits: int) -> Column:
    """Edit distance of columns x and y, arrays of characters with x no shorter, if at most edits, else null.

    After j characters of y, bit k of vp (vn) says that row j - edits + k of the table is
    one more (less) than the row above it. d follows the diagonal that ends in the last
    cell, where it never shrinks: it grows where bit k of d0, "as on the diagonal before",
    is not set, and past edits nothing more is computed.
    """
    w = 2 * edits + 1
    full = (1 << w) - 1
    match = " | ".join(f"if(get({x}, j + {k - edits}) <=> {y}[j], {1 << k}, 0)" for k in range(w))
    d0 = f"(((((pm & s.vp) + s.vp) ^ s.vp) | pm | s.vn) & {full})"
    hp = "(e.vn | ~(e.d0 | e.vp))"
    start = f"named_struct('vp', {full & ~((1 << edits) - 1)}, 'vn', 0, 'd', size({x}) - size({y}))"
    step = f"""transform(transform(array({match}), pm -> named_struct('d0', {d0}, 'vp', s.vp, 'vn', s.vn, 'd', s.d)),
        e -> named_struct('vp', ((e.d0 & e.vp) | ~(shiftright(e.d0, 1) | {hp})) & {full},
                          'vn', shiftright(e.d0, 1) & {hp} & {full},
                          'd', e.d + 1 - (shiftright(e.d0, {edits} + size({x}) - size({y})) & 1)))[0]"""
    run = f"aggregate(sequence(0, size({y}) - 1), {start}, (s, j) -> if(s.d > {edits}, s, {step}), s -> if(s.d <= {edits}, s.d, null))"
    return F.expr(f"if(size({x}) - size({y}) <= {edits}, if(size({y}) = 0, size({x}), {run}), null)")


def letter_pairs(df: DataFrame) -> DataFrame:
    """Adds bag: hashes of the neighbouring letters of norm, each numbered by how many equal ones come before it."""
    one = _held(df, "_f", F.expr("array_sort(transform(sequence(1, greatest(length(norm) - 1, 1)), i -> substr(norm, i, 2)))"))
    one = _held(one, "_at", F.expr("filter(sequence(0, size(_f) - 1), i -> i = 0 or _f[i] <> _f[i - 1])"))
    runs = "transform(_at, (a, k) -> transform(sequence(0, coalesce(get(_at, k + 1), size(_f)) - a - 1), o -> xxhash64(_f[a], o)))"
    return one.withColumn("bag", F.expr(f"flatten({runs})")).drop("_f", "_at")


def _verified(pairs: DataFrame, texts: DataFrame, edits: int) -> DataFrame:
    """pairs: h_a, h_b. Those within the edits that the shorter one allows, with both lines' columns and edits."""
    side = lambda c: texts.select(*[F.col(k).alias(f"{k}_{c}") for k in ("h", "h2", "norm", "doc", "th", "line_no")])
    both = pairs.join(side("a"), "h_a").join(side("b"), "h_b").withColumn("e", allowed(F.least(F.length("norm_a"), F.length("norm_b")), edits))
    both = both.where(letters_near(F.col("norm_a"), F.col("norm_b"), F.col("e")))
    cells = differing(both, "norm_a", "norm_b")
    near = cells.withColumn("edits", F.explode_outer(F.array(within_edits("x", "y", edits)))).drop("x", "y")
    return near.where(F.col("edits") <= F.col("e"))


def _ends(near: DataFrame) -> DataFrame:
    """h, h2 of the later line of each verified pair, and the earlier one's place."""
    place = lambda c: F.struct(f"doc_{c}", f"th_{c}", f"line_no_{c}")
    late = F.when(place("a") < place("b"), "b").otherwise("a")
    pick = lambda k, which: F.when(late == which, F.col(f"{k}_a")).otherwise(F.col(f"{k}_b"))
    return near.select(pick("h", "a").alias("h"), pick("h2", "a").alias("h2"), *[pick(k, "b").alias(k) for k in ("doc", "th", "line_no")], "edits")


def _maybe(rows: DataFrame, wanted: DataFrame) -> DataFrame:
    """The rows whose h may be wanted, by a table of bits of a bounded size, ahead of the join that decides."""
    words = min(MOST_WORDS, max(1 << 10, 1 << (wanted.count() // 8).bit_length()))
    word = f"shiftrightunsigned(h, 6) % {words}"
    bits = wanted.select(F.expr(word).alias("_w"), F.expr("shiftleft(1L, int(h & 63))").alias("_b")).groupBy("_w").agg(F.bit_or("_b").alias("_b"))
    held = rows.withColumn("_w", F.expr(word)).join(F.broadcast(bits), "_w")  # at most MOST_WORDS rows of two longs
    return held.where(F.expr("shiftrightunsigned(_b, int(h & 63)) & 1 = 1")).drop("_w", "_b")


def _texts(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """h, h2, norm and the first place of the lines whose h is wanted, read from the documents again."""
    wanted = stored(wanted, "line-wanted")
    one = _maybe(placed_lines(docs, CHARS_AN_EDIT).drop("n"), wanted).join(wanted, "h").groupBy("h", "h2").agg(F.min(F.struct("doc", "th", "line_no", "norm")).alias("one"))
    return one.select("h", "h2", "one.*")


def _often(members: DataFrame, found: DataFrame, edits: int) -> tuple[DataFrame, DataFrame]:
    """Pairs of lines that share a frequent segment.

    members: key, h, sk, e, ix of those segments; found: texts, as _texts gives. Returns
    verified pairs with each segment's leader, and h_a, h_b of the other pairs that letter
    pairs don't rule out.
    """
    few = 2 * edits
    texts = stored(letter_pairs(found.join(members.select("h").distinct(), "h")), "line-often-texts")
    place = F.struct("doc", "th", "line_no")
    rows = members.join(texts.select("h", place.alias("place"), sketch(F.col("norm"), RARER[:8]).alias("rk")), "h")
    lead = rows.groupBy("key").agg(F.min(F.struct("place", "h")).alias("lead")).select("key", F.col("lead.h").alias("lead"))
    rows = stored(rows.join(lead, "key"), "line-often-led")
    own = rows.select("h", "lead").where("h <> lead").distinct()
    near = stored(_verified(own.select(F.col("h").alias("h_a"), F.col("lead").alias("h_b")), texts, edits), "line-led")
    close = near.select(F.col("h_a").alias("h"), F.col("h_b").alias("lead"), F.lit(True).alias("close")).distinct()
    bags = own.join(texts.select("h", "bag"), "h").join(texts.select(F.col("h").alias("lead"), F.col("bag").alias("of_lead")), "lead")
    sides = F.expr("array(struct(0 as side, array_except(bag, of_lead) as t), struct(1 as side, array_except(of_lead, bag) as t))")
    apart = bags.select("h", "lead", F.explode(sides).alias("s")).select("h", "lead", "s.side", F.explode("s.t").alias("t"))
    # the rarer a pair among the leader's lines, the earlier in the order: what all of them have besides it tells none apart
    rare = apart.groupBy("lead", "side", "t").agg(F.count("*").alias("n"))
    order = F.expr(f"transform(slice(sort_array(collect_list(struct(n, t))), 1, {few + 1}), x -> x.t)")
    first = stored(apart.join(rare, ["lead", "side", "t"]).groupBy("h", "lead", "side").agg(order.alias("t")), "line-apart")
    of_side = lambda i, name: first.where(F.col("side") == i).select("h", "lead", F.col("t").alias(name))
    zero = F.array(F.lit(0).cast("long"))
    marks = lambda c: F.when(F.size(c) > few, F.col(c)).otherwise(F.concat(F.coalesce(F.col(c), F.array().cast("array<bigint>")), zero))
    told = own.join(of_side(0, "_m"), ["h", "lead"], "left").join(of_side(1, "_l"), ["h", "lead"], "left").select("h", "lead", marks("_m").alias("more"), marks("_l").alias("less"))
    told = stored(told.join(close, ["h", "lead"], "left").withColumn("close", F.coalesce("close", F.lit(False))), "line-told")
    # the leader itself has been compared with all; a line near it needs no other earlier one here
    cells = rows.join(told, ["h", "lead"]).withColumn("cell", F.explode(F.expr("flatten(transform(more, m -> transform(less, l -> xxhash64(key, m, l))))")))
    cells = stored(cells.select("cell", "h", "sk", "rk", "e", "ix", "close", "place"), "line-cells")
    later = cells.where("not close").select("cell", F.col("h").alias("ph"), F.col("sk").alias("psk"), F.col("rk").alias("prk"), F.col("e").alias("pe"), F.col("ix").alias("pix"), F.col("place").alias("pp"))
    fits = (F.col("place") < F.col("pp")) & (F.col("ix") | F.col("pix")) & sketch_near(F.col("sk"), F.col("psk"), F.least("e", "pe")) & sketch_near(F.col("rk"), F.col("prk"), F.least("e", "pe"), RARER[:8])
    met = cells.join(later, "cell").where(fits).select(F.least("h", "ph").alias("h_a"), F.greatest("h", "ph").alias("h_b"))
    return near, met


def near_lines(docs: DataFrame, all_lines: DataFrame, several: DataFrame, edits: int = EDITS, often: int = OFTEN) -> DataFrame:
    """h, h2 of the lines near an earlier one, and the earliest such.

    all_lines: as `lines` gives of docs; several: h, h2, first and n of those that stand more than once.
    """
    n = F.col("n")
    # of lines with many copies only the first is looked up; a few equal rows more do no harm
    copied = stored(several.where(F.col("n") > COPIES).select("h", "h2", "first"), "line-copied")
    keys = all_lines.where(n >= CHARS_AN_EDIT).select("h", "h2", "doc", "th", "line_no", "n", "sk", "ix", "pr").join(copied, ["h", "h2"], "left")
    keys = keys.where(F.col("first").isNull() | (F.col("first") == F.struct("doc", "th", "line_no")))
    keyed = lambda of, ix: keys.select("h", "sk", allowed(n, edits).alias("e"), F.lit(ix).alias("ix"), F.explode_outer(of).alias("key"))
    indexed, probes = keyed("ix", True), keyed("pr", False)
    frequent = stored(indexed.groupBy("key").agg(F.count("*").alias("m")).where(F.col("m") > often).select("key"), "line-frequent")
    usual = lambda df: df.join(frequent, "key", "left_anti").select("key", "h", "sk", "e")
    a = usual(indexed)  # both sides read the same columns, so that it is shuffled once for all three places

    def meet(right: DataFrame, once: bool) -> DataFrame:
        x, y = a.alias("x"), right.alias("y")
        fits = sketch_near(F.col("x.sk"), F.col("y.sk"), F.least("x.e", "y.e"))
        order = F.col("x.h") < F.col("y.h") if once else F.col("x.h") != F.col("y.h")
        return x.join(y, F.col("x.key") == F.col("y.key")).where(order & fits).select(F.least("x.h", "y.h").alias("h_a"), F.greatest("x.h", "y.h").alias("h_b"))

    members = stored(indexed.unionByName(probes).join(frequent, "key", "left_semi").distinct(), "line-often")
    met = stored(meet(a, True).unionByName(meet(usual(probes), False)).distinct(), "line-pairs")
    texts = stored(_texts(docs, met.select(F.col("h_a").alias("h")).union(met.select("h_b")).union(members.select("h")).distinct()), "line-texts")
    led, more = _often(members, texts, edits)
    near = stored(_verified(met.unionByName(more).distinct(), texts, edits), "line-verified")
    return _ends(near).unionByName(_ends(led)).groupBy("h", "h2").agg(F.min(F.struct("doc", "th", "line_no", "edits")).alias("by"))


def duplicate_lines(docs: DataFrame, edits: int = EDITS, least_chars: int = LEAST_CHARS) -> DataFrame:
    """doc, th, line_no, of_doc, of_line_no, edits of every line that goes."""
    all_lines = stored(lines(docs, least_chars, edits), "lines")
    several = stored(repeated(all_lines), "line-firsts")
    near = stored(near_lines(docs, all_lines, several, edits), "line-near")
    judged = all_lines.select("doc", "th", "line_no", "h", "h2").join(several, ["h", "h2"], "left").join(near, ["h", "h2"], "left")
    equal = F.col("first").isNotNull() & (F.col("first") != F.struct("doc", "th", "line_no"))
    return judged.where(equal | F.col("by").isNotNull()).select(
        "doc", "th", "line_no", F.coalesce(F.when(equal, F.col("first.doc")), F.col("by.doc")).alias("of_doc"),
        F.coalesce(F.when(equal, F.col("first.line_no")), F.col("by.line_no")).alias("of_line_no"), F.when(equal, 0).otherwise(F.col("by.edits")).alias("edits"),
    )


def repeated(all_lines: DataFrame) -> DataFrame:
    """h, h2, first place and number of the lines that stand more than once."""
    firsts = all_lines.groupBy("h", "h2").agg(F.min(F.struct("doc", "th", "line_no")).alias("first"), F.count("*").alias("n"))
    return firsts.where("n > 1")


def without_duplicate_lines(docs: DataFrame, edits: int = EDITS, least_chars: int = LEAST_CHARS, drop_emptied: bool = False) -> DataFrame:
    """docs with the lines gone from text (and n_chars counted anew where a text changed), all columns and rows.

    Decided on distinct texts: copies of a whole text keep what their first one keeps, for
    document-level operators to find. drop_emptied: without the rows that had lines and have none left.
    """
    texts = docs.where(F.col("text").isNotNull()).groupBy(F.xxhash64("text").alias("th")).agg(F.min(F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63)))).alias("doc"))
    own = docs.select(F.col("text"), F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63))).alias("doc_id"), F.xxhash64("text").alias("_th"))
    own = own.join(texts, (own["_th"] == texts["th"]) & (own["doc_id"] == texts["doc"]), "left_semi").select("doc_id", "text")
    gone = stored(duplicate_lines(own, edits, least_chars).groupBy("th").agg(F.collect_set("line_no").alias("gone")), "line-gone")
    names = docs.columns
    # the row goes along whole, so that none of its names can clash
    held = docs.select(F.struct(*[docs[c] for c in names]).alias("row"), F.xxhash64(docs["text"]).alias("th")).join(gone, "th", "left")
    left = F.expr("array_join(filter(split(row.text, '\n'), (x, i) -> not array_contains(gone, i)), '\n')")
    # where blank lines alone are left, nothing is
    left = F.when(F.trim(F.regexp_replace(left, r"\s+", " ")) == "", F.lit("")).otherwise(left)
    out = _held(held, "new", F.when(F.col("gone").isNull(), F.col("row.text")).otherwise(left))
    if drop_emptied:
        out = out.where(F.col("gone").isNull() | (F.col("new") != ""))
    cols = {"text": F.col("new")}
    if "n_chars" in names:
        cols["n_chars"] = F.when(F.col("new") != F.col("row.text"), F.length("new").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("row.n_chars"))
    return out.select(*[cols.get(c, F.col("row")[c]).alias(c) for c in names])
