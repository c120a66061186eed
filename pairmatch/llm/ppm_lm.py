"""Language-model scores by prediction by partial matching over bytes.

The training texts give the counts of a byte trie of bounded depth: for each context
of up to ORDER bytes, how often each byte followed. A byte's probability is its share
in the longest known context, or, by an escape of as many counts as the context has
different followers, its share in the next shorter one without the bytes that the
longer one would have predicted (symbol exclusion), down to equal shares. A shorter
context knows every byte a longer one knows, so that exclusion needs one sum a
context, and the whole trie is a handful of grouped tables.

No task holds the trie. Documents are dealt into blocks of a bounded size; a block
asks for the trie's values of its own distinct byte strings, and for the counts of
its own distinct words, and is scored with what it was sent.

Defined results: null text is the empty text, which costs the end mark alone; NUL
bytes count as byte 1, since NUL marks both ends; repeated rows are scored each; rows
with a null id are scored, learnt from, and never held out; with no training rows
every byte costs log10(1/256) and the base score is 0; an empty table gives no row;
texts of any length are scored whole, and a block holds one at least.
"""

from __future__ import annotations

import math
from collections import Counter

from pyspark.sql import Column, DataFrame, functions as F

from pairmatch.llm import common
from pairmatch.llm.common import give_back

ORDER = 5
BLOCK_BYTES = 16_000_000
FLUSH_BYTES = 1_000_000
MERGE_CODES = 2_000_000
FLUSH_WORDS = 600_000
WORD_BYTES = 4_000_000
MANY = 64  # blocks that a mask tells apart
MASK = [(1 << 8 * (j + 1)) - 1 for j in range(ORDER + 1)]


CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def stored(df: DataFrame, name: str) -> DataFrame:
    """A stored table; what was shuffled to make it goes once it is written, where Spark can do that (from 4.1 on)."""
    conf = df.sparkSession.conf
    was = conf.get(CLEANUP, None)
    if was is None:
        return common.stored(df, name)
    conf.set(CLEANUP, "true")
    try:
        return common.stored(df, name)
    finally:
        conf.set(CLEANUP, was)


def clean(text: str | None) -> bytes:
    return (text or "").encode("utf-8", "replace").lower().replace(b"\0", b"\1")


def grams(texts: list[bytes]):
    """Codes of (context, byte) at every place of the texts, -1 where a text's pads are; and where each text begins."""
    import numpy as np

    sizes = np.array([len(t) + 1 + ORDER for t in texts], np.int64)
    raw = b"\0" * ORDER + (b"\0" + b"\0" * ORDER).join(texts) + b"\0" * 8
    n = int(sizes.sum()) - ORDER
    code = np.ndarray((n,), ">u8", raw, 0, (1,)).astype(np.int64)
    code >>= 8 * (7 - ORDER)
    code &= MASK[ORDER]
    starts = np.r_[0, np.cumsum(sizes)[:-1]]
    pads = (starts[1:, None] - 1 - np.arange(ORDER)[None, :]).ravel()
    code[pads] = -1
    return code, starts


def distinct(code):
    """Sorted distinct codes without the pads' mark; a sort, as hashing that many costs several times more."""
    import numpy as np

    code = np.sort(code)
    new = np.ones(len(code), bool)
    np.not_equal(code[1:], code[:-1], out=new[1:])
    keys = code[new]
    return keys[int(len(keys) > 0 and keys[0] == -1) :]


def counted(code):
    """The same with their counts."""
    import numpy as np

    keys, n = np.unique(code, return_counts=True)
    skip = int(len(keys) > 0 and keys[0] == -1)
    return keys[skip:], n[skip:]


def taught_counts(code, taught):
    """Distinct codes without the pads' mark, and how many of their places are taught ones; one sort of code and mark together."""
    import numpy as np

    both = code * 2 + taught
    both.sort()
    code = both >> 1
    new = np.ones(len(code), bool)
    np.not_equal(code[1:], code[:-1], out=new[1:])
    first = np.flatnonzero(new)
    keys, n = code[first], (np.add.reduceat(both & 1, first) if len(first) else both).astype(np.int32)
    skip = int(len(keys) > 0 and keys[0] == -1)
    return keys[skip:], n[skip:]


def merge(parts: list):
    import numpy as np

    if not parts:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    if len(parts) == 1:
        return parts[0]
    keys = np.concatenate([p[0] for p in parts])
    order = np.argsort(keys, kind="stable")  # takes sorted runs as they are
    keys, n = keys[order], np.concatenate([p[1] for p in parts])[order]
    first = np.flatnonzero(np.r_[len(keys) > 0, keys[1:] != keys[:-1]])
    return keys[first], (np.add.reduceat(n, first) if len(first) else n).astype(n.dtype)


def slices(texts):
    """A column of texts in runs of rows of WORD_BYTES, a row at least."""
    import pyarrow.compute as pc

    first, size = 0, 0
    for i, n in enumerate(pc.fill_null(pc.binary_length(texts), 0).to_pylist()):
        if size and size + n + 64 > WORD_BYTES:
            yield texts.slice(first, i - first)
            first, size = i, 0
        size += n + 64
    if size:
        yield texts.slice(first)


def words_of(texts):
    """All words of a column of texts, one after the other, and where each text's begin and end."""
    import numpy as np
    import pyarrow as pa
    import pyarrow.compute as pc

    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    lists = pc.ascii_split_whitespace(pc.ascii_lower(pc.fill_null(texts, "")))
    flat = lists.flatten()
    full = pc.not_equal(flat, "")  # white space at an end leaves an empty word there
    at = np.r_[0, np.cumsum(pc.list_value_length(lists).to_numpy(zero_copy_only=False))].astype(np.int64)
    return flat.filter(full), np.r_[0, np.cumsum(full.to_numpy(zero_copy_only=False))][at].tolist()


def _count_words(batches):
    import pyarrow as pa

    def rows(c):
        return pa.record_batch([pa.array(list(c), pa.string()), pa.array(list(c.values()), pa.int64())], names=["word", "n"])

    c: Counter = Counter()
    for batch in batches:
        for some in slices(batch.column(0)):
            word, n = words_of(some)[0].value_counts().flatten()
            c.update(dict(zip(word.to_pylist(), n.to_pylist(), strict=True)))
            if len(c) > FLUSH_WORDS:
                yield rows(c)
                c = Counter()
    if c:
        yield rows(c)
    del c
    give_back()


class Trie:
    """Grouped tables of the trie: counts by order, and what exclusion needs by context.

    counts: g, n, several rows a code unless `single`, when it is a stored table; codes
    that no training text has come with n = 0.
    """

    def __init__(self, counts: DataFrame, single: bool = False):
        self.codes = counts if single else stored(counts.groupBy("g").agg(F.sum("n").alias("n")), "ppm-counts")
        self.counts = {ORDER: self.codes.where("n > 0")}
        for j in range(ORDER - 1, -1, -1):
            self.counts[j] = stored(self.counts[j + 1].groupBy(F.col("g").bitwiseAND(MASK[j]).alias("g")).agg(F.sum("n").alias("n")), f"ppm-counts-{j}")
        self.contexts = {j: self._context(j) for j in range(ORDER, -1, -1)}

    def _context(self, j: int) -> DataFrame:
        """c, total and followers; below: the followers' counts one order lower."""
        rows = self.counts[j].select(F.shiftright("g", 8).alias("c"), "g", "n")
        if j:
            lower = self.counts[j - 1].select(F.col("g").alias("s"), F.col("n").alias("m"))
            rows = rows.withColumn("s", F.col("g").bitwiseAND(MASK[j - 1])).join(lower, "s")
        else:
            rows = rows.withColumn("m", F.lit(0).cast("long"))
        return rows.groupBy("c").agg(F.sum("n").alias("total"), F.count("*").alias("followers"), F.sum("m").alias("below"))

    def log10_p(self, asked: DataFrame) -> DataFrame:
        """g, lp for distinct codes g."""
        found = []
        zero = F.lit(0).cast("long")
        rest = asked.select("g", F.lit(0.0).alias("lp"), zero.alias("out_n"), zero.alias("out_t"))
        for j in range(ORDER, -1, -1):
            seen = self.counts[j].select(F.col("g").alias("s"), F.col("n").alias("m"))
            ctx = self.contexts[j]
            rest = (
                rest.withColumn("s", F.col("g").bitwiseAND(MASK[j])).withColumn("c", F.shiftright("s", 8))
                .join(seen, "s", "left").join(ctx, "c", "left")
            )
            n, t = F.col("total") - F.col("out_n"), F.col("followers") - F.col("out_t")
            hit, known = F.col("m").isNotNull(), F.col("followers").isNotNull()
            escape = F.when(known & (t > 0), F.log10(t / (n + t))).otherwise(0.0)
            lp = F.col("lp") + F.when(hit, F.log10(F.col("m") / (n + t))).otherwise(escape)
            left_out = lambda c: F.when(~hit, F.when(known, F.col(c)).otherwise(zero))
            # sums of the next order alone are kept, and none where the byte was found
            rest = stored(rest.select("g", lp.alias("lp"), left_out("below").alias("out_n"), left_out("followers").alias("out_t")), f"ppm-order-{j}")
            found.append(rest.where("out_n is null").select("g", "lp"))
            rest = rest.where("out_n is not null")
        found.append(rest.select("g", (F.col("lp") - F.log10(F.greatest(F.lit(256) - F.col("out_t"), F.lit(1)))).alias("lp")))
        out = found[0]
        for x in found[1:]:
            out = out.unionByName(x)
        return out


def askers(asked: DataFrame) -> DataFrame:
    """g, many, mask, n: bit k of mask says that block MANY * many + k asks for g; n is the count over these blocks."""
    bit = F.expr(f"shiftleft(1L, block % {MANY})").alias("mask")
    rows = asked.where("g is not null").select("g", F.expr(f"int(block div {MANY})").alias("many"), bit, F.col("n").cast("long").alias("n"))
    return rows.groupBy("g", "many").agg(F.bit_or("mask").alias("mask"), F.sum("n").alias("n"))


def asking_blocks(blocks: int) -> Column:
    """The blocks that columns many and mask name, four bits at a time by tables."""
    parts = []
    for low in range(0, min(blocks, MANY), 4):
        sets = [", ".join(str(low + i) for i in range(4) if x >> i & 1) for x in range(16)]
        choices = ", ".join(f"cast(array({x}) as array<int>)" for x in sets)
        parts.append(f"get(array({choices}), int(shiftrightunsigned(mask, {low}) & 15))")
    return F.expr(f"concat({', '.join(parts)})")


def _asks(key, table):
    """Distinct codes of a block, each with its count in the block's training texts, and distinct words."""
    import numpy as np
    import pyarrow as pa

    parts, texts, marks, size = [], [], [], 0
    col, learn = table.column("text"), table.column("learn").to_pylist()
    for i in range(len(col) + 1):
        if i == len(col) or size > FLUSH_BYTES:
            if texts:
                code, starts = grams(texts)
                parts.append(taught_counts(code, np.repeat(np.array(marks, np.int64), np.diff(np.r_[starts, len(code)]))))
                del code
                if sum(len(p[0]) for p in parts[1:]) > max(MERGE_CODES, len(parts[0][0])):
                    parts = [merge(parts)]
            texts, marks, size = [], [], 0
        if i < len(col):
            texts.append(clean(col[i].as_py()))
            marks.append(bool(learn[i]))
            size += len(texts[-1]) + 64
    g, n = merge(parts)
    del parts
    w = pa.chunked_array([words_of(some)[0].unique().cast(pa.string()) for some in slices(col)], pa.string()).unique()
    give_back()
    block = pa.array(np.full(len(g) + len(w), key[0].as_py(), np.int32))
    return pa.table({"block": block, "g": pa.concat_arrays([pa.array(g, pa.int64()), pa.nulls(len(w), pa.int64())]), "n": pa.concat_arrays([pa.array(n.astype(np.int32), pa.int32()), pa.nulls(len(w), pa.int32())]), "word": pa.concat_arrays([pa.nulls(len(g), pa.string()), w])})


class Lookup:
    """Values of known codes: one probe for most, a binary search for the rest."""

    def __init__(self, keys, values):
        import numpy as np

        order = np.argsort(keys)
        self.keys, self.values = keys[order], values[order]
        self.bits = max(4, int(len(keys)).bit_length() + 2)
        self.slot = np.zeros(1 << self.bits, np.int32)
        self.slot[self._hash(self.keys)] = np.arange(len(keys))

    def _hash(self, q):
        import numpy as np

        return ((q.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def __call__(self, q):
        import numpy as np

        at = self.slot[self._hash(q)]
        miss = np.flatnonzero(self.keys[at] != q)
        at[miss] = np.minimum(np.searchsorted(self.keys, q[miss]), len(self.keys) - 1)
        out = self.values[at]
        out[q < 0] = 0.0  # pads
        return out


def _score_block(end_log: float, log_all: float):
    def run(key, docs, sent):
        import numpy as np
        import pyarrow as pa
        import pyarrow.compute as pc

        coded = sent.filter(pc.is_valid(sent.column("g"))).select(["g", "v"])
        look = Lookup(coded.column("g").to_numpy(), coded.column("v").to_numpy()) if len(coded) else None
        del coded
        named = sent.filter(pc.is_valid(sent.column("word"))).select(["word", "v"])
        known, v = named.column("word").combine_chunks(), named.column("v").to_numpy()
        del named, sent

        def logs():
            for some in slices(docs.column("text")):
                words, ends = words_of(some)
                found = v[pc.index_in(words, value_set=known.cast(words.type)).to_numpy(zero_copy_only=False)] if len(words) else v[:0]
                for a, b in zip(ends, ends[1:]):
                    yield found[a:b].tolist()

        score, base, n_tokens, n_known, pending, size = [], [], [], [], [], 0
        for i, (text, of_words) in enumerate(zip(docs.column("text"), logs(), strict=True)):
            got = of_words + [end_log]
            n_tokens.append(len(got))
            n_known.append(len(got) - got.count(0.0))
            base.append(math.fsum(got) - len(got) * log_all)
            pending.append(clean(text.as_py()))
            size += len(pending[-1]) + 64
            if size > FLUSH_BYTES or i == len(docs) - 1:
                code, starts = grams(pending)
                score += np.add.reduceat(look(code), starts).tolist()
                pending, size = [], 0
        del look, known, v
        give_back()
        return pa.table({"doc_id": docs.column("doc_id"), "n_tokens": pa.array(n_tokens, pa.int64()), "n_known": pa.array(n_known, pa.int64()), "base_score": pa.array(base, pa.float64()), "score": pa.array(score, pa.float64())})

    return run


def score_documents(docs: DataFrame, learn) -> DataFrame:
    """doc_id, n_tokens, n_known, train_tokens, base_score, score of every document.

    learn: which rows to learn from, as a Column over docs.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), learn.alias("learn"))
    taught = docs.where("learn").select("text")
    words = stored(taught.mapInArrow(_count_words, "word string, n long").groupBy("word").agg(F.sum("n").alias("n")), "ppm-words")
    n_docs = taught.count()
    all_words = words.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.count("*").alias("v")).first()
    train_tokens, distinct = all_words["n"] + n_docs, all_words["v"] + (n_docs > 0)

    total = docs.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0)).alias("b"), F.count("*").alias("n")).first()
    blocks = max(1, -(-(total["b"] + 64 * total["n"]) // BLOCK_BYTES))
    dealt = docs.select(F.pmod(F.xxhash64("doc_id", "text"), F.lit(blocks)).cast("int").alias("block"), "doc_id", "text", "learn")
    # a block's codes come with their counts in its training texts, so that texts are cut into codes once for both
    asked = stored(dealt.groupBy("block").applyInArrow(_asks, "block int, g long, n int, word string"), "ppm-asked")
    # a code with the blocks that ask for it is one row for up to MANY of them, and goes to each with its value at the end alone
    masks = stored(askers(asked), "ppm-askers")
    trie = Trie(masks.select("g", "n"), single=blocks <= MANY)
    values = trie.log10_p(trie.codes.select("g"))
    coded = masks.select("g", "many", "mask").join(values, "g").select("g", "lp", "many", F.explode(asking_blocks(blocks)).alias("k"))
    sent = (
        coded.select((F.col("many") * MANY + F.col("k")).cast("int").alias("block"), "g", F.lit(None).cast("string").alias("word"), F.col("lp").alias("v"))
        .unionByName(
            asked.where("word is not null").select("block", "word").join(words, "word", "left")
            .select("block", F.lit(None).cast("long").alias("g"), "word", F.log10(F.coalesce("n", F.lit(0)) + 1.0).cast("double").alias("v"))
        )
    )
    run = _score_block(math.log10(n_docs + 1), math.log10(train_tokens + distinct + 1))
    out = dealt.drop("learn").groupBy("block").cogroup(sent.groupBy("block")).applyInArrow(run, "doc_id long, n_tokens long, n_known long, base_score double, score double")
    return out.select("doc_id", "n_tokens", "n_known", F.lit(train_tokens).cast("long").alias("train_tokens"), "base_score", "score")
