"""Near duplicates by b-bit MinHash: banded candidates, corrected estimates, exact links.

A document's set is its distinct five-word shingles. Equal sets become one class.
Classes get HASHES minima; BANDS bands of full minima give buckets, and of each minimum
BITS low bits are kept, packed into longs, for estimates by bit counts corrected for
chance collisions. What the estimate cannot rule out is confirmed on full sets.

Only components matter, so members of a bucket first meet a few leaders of it, each
round others, and only pairs that are still in different components. What then still
shares a bucket across components is compared on full sets in blocks, of which only
the links that join components come out. No pair within a component is made.

Defined results: null or wordless texts have the empty set and are linked with nothing;
with fewer words than a shingle the whole sequence is the one shingle; rows that repeat
an id are one document (its links are those of all its texts that have words); rows with
a null id are returned with a null component and kept; an empty table gives no row; texts
of any length are read whole.

Links are exact, candidates are not certain: the bands miss a pair of similarity 0.85
with a chance of 7e-6 and one of 0.80 with 2e-4, the estimate's cut rules out one in
300,000 more; a pair counts only where no other path joins its documents.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

from pairmatch.llm.common import give_back, lean, stored, stored_lean
from pairmatch.llm.components import components

HASHES, BANDS, BITS = 64, 16, 4
ROWS = HASHES // BANDS
STAR_ROUNDS = 3
WORD = 5
NIBBLE = 0x1111111111111111
BLOCK = 256
CELLS = 1 << 20  # of a slice of the sets of a block pair, as a table of members


def shingles(text: str | None, words: int = WORD):
    """Sorted distinct 64-bit hashes of the text's shingles."""
    import numpy as np
    import xxhash

    w = (text or "").encode("utf-8", "replace").lower().split()
    if not w:
        return np.zeros(0, np.uint64)
    if len(w) < words:
        return np.array([xxhash.xxh3_64_intdigest(b" ".join(w))], np.uint64)
    h = xxhash.xxh3_64_intdigest
    j = b" ".join
    return np.unique(np.fromiter((h(j(w[i : i + words])) for i in range(len(w) - words + 1)), np.uint64, len(w) - words + 1))


def coefficients():
    import numpy as np

    rng = np.random.default_rng(20240131)
    return rng.integers(0, 1 << 32, HASHES, np.uint32) | np.uint32(1), rng.integers(0, 1 << 32, HASHES, np.uint32)


def minima(s, a, b):
    """HASHES 32-bit minima of a non-empty set."""
    import numpy as np

    low = (s ^ (s >> np.uint64(32))).astype(np.uint32)
    best = np.full(HASHES, 0xFFFFFFFF, np.uint32)
    for i in range(0, len(low), 2048):
        v = low[None, i : i + 2048] * a[:, None]
        v += b[:, None]
        np.minimum(best, v.min(1), out=best)
    return best


def _sign(batches):
    import numpy as np
    import pyarrow as pa

    a, b = coefficients()
    names = ["doc_id", "th", "n_shingles", "f1", "f2", "bands", "packed"]
    types = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int64())]
    import xxhash

    for batch in batches:
        rows = []
        for doc_id, text, th in zip(batch.column(0), batch.column(1), batch.column(2), strict=True):
            s = shingles(text.as_py())
            if not len(s):
                rows.append((doc_id.as_py(), th.as_py(), 0, 0, 0, None, None))
                continue
            f = xxhash.xxh3_128_digest(s.tobytes())
            m = minima(s, a, b)
            mixed = (m ^ (m >> np.uint32(15))) * np.uint32(0x2C1B3C6D)
            nib = ((mixed >> np.uint32(12)) & np.uint32(15)).astype(np.uint64).reshape(-1, 16)
            packed = (nib << (np.arange(16, dtype=np.uint64) * np.uint64(4))).sum(1, dtype=np.uint64).view(np.int64)
            bands = [xxhash.xxh3_64_intdigest(bytes([i]) + x.tobytes()) for i, x in enumerate(m.reshape(BANDS, ROWS))]
            f1, f2 = np.frombuffer(f, np.int64).tolist()
            rows.append((doc_id.as_py(), th.as_py(), len(s), f1, f2, np.array(bands, np.uint64).view(np.int64).tolist(), packed.tolist()))
        yield pa.record_batch([pa.array(c, t) for c, t in zip(zip(*rows, strict=True) if rows else [[]] * 7, types, strict=True)], names=names)



def signatures(docs: DataFrame) -> DataFrame:
    """doc_id, text hash, n_shingles, two halves of the set's fingerprint, bands and packed bits (null for empty sets)."""
    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"), F.xxhash64("text").alias("th")).mapInArrow(
        lean(_sign), "doc_id long, th long, n_shingles long, f1 long, f2 long, bands array<long>, packed array<long>"
    )


def estimate(p: Column, q: Column) -> Column:
    """Similarity from packed low bits, corrected for minima that differ but agree in them."""
    unequal = F.lit(0)
    for i in range(HASHES // 16):
        x = p[i].bitwiseXOR(q[i])
        x = x.bitwiseOR(F.shiftrightunsigned(x, 2))
        x = x.bitwiseOR(F.shiftrightunsigned(x, 1))
        unequal = unequal + F.bit_count(x.bitwiseAND(NIBBLE))
    chance = 1.0 / (1 << BITS)
    return ((HASHES - unequal) / HASHES - chance) / (1 - chance)


def _sets(batches):
    import pyarrow as pa

    for batch in batches:
        sets = [shingles(t.as_py()).tobytes() for t in batch.column(1)]
        yield pa.record_batch([batch.column(0), pa.array(sets, pa.binary())], names=["id", "items"])


def _confirm(percent: int):
    def run(batches):
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2), batch.column(3), strict=True):
                p, q = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                common = len(np.intersect1d(p, q, assume_unique=True))
                keep.append(100 * common >= percent * (len(p) + len(q) - common))
            yield batch.select([0, 1]).filter(pa.array(keep, pa.bool_()))

    return run


def _blocks(percent: int):
    """Links between the documents of a block pair, one for each two components that they join."""

    def run(key, table):
        import numpy as np
        import pyarrow as pa

        ids, roots, side = (table.column(c).to_numpy() for c in ("id", "root", "side"))
        sets = [np.frombuffer(x.as_buffer(), np.uint64) for x in table.column("items")]
        size = np.array([len(x) for x in sets])
        group: dict[int, int] = {}

        def top(r):
            while group.get(r, r) != r:
                r = group[r]
            return r

        sides = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
        a, b = sides if len(sides[1]) else (sides[0], sides[0])
        maybe = (100 * np.minimum(size[a][:, None], size[b][None, :]) >= percent * np.maximum(size[a][:, None], size[b][None, :])) & (roots[a][:, None] != roots[b][None, :])
        flat, owner = np.concatenate(sets), np.repeat(np.arange(len(sets), dtype=np.int32), size)
        order = np.argsort(flat, kind="stable")
        flat, owner = flat[order], owner[order]
        new = np.r_[True, flat[1:] != flat[:-1]]
        often = ~new | np.r_[flat[1:] == flat[:-1], False]  # items of one set alone are in no intersection
        owner, column = owner[often], np.cumsum(new[often], dtype=np.int32) - 1
        del flat, order, new, often
        common, wide = np.zeros((len(a), len(b)), np.float32), max(1, CELLS // len(sets))
        for at in range(0, int(column[-1]) + 1 if len(column) else 0, wide):
            lo, hi = np.searchsorted(column, (at, at + wide))
            m = np.zeros((len(sets), wide), np.float32)
            m[owner[lo:hi], column[lo:hi] - at] = 1
            common += m[a] @ m[b].T
        linked = np.argwhere(maybe & (100 * common >= percent * (size[a][:, None] + size[b][None, :] - common)))
        out = []
        for i, j in linked:
            p, q = top(roots[a[i]]), top(roots[b[j]])
            if p != q:
                group[p] = q
                out.append((ids[a[i]], ids[b[j]]))
        del sets, table, common
        give_back()
        return pa.table({"a": pa.array([x for x, _ in out], pa.int64()), "b": pa.array([x for _, x in out], pa.int64())})

    return run


def _rest(cells: DataFrame, labels: DataFrame, items: DataFrame, percent: int) -> DataFrame:
    """Links among documents that share a bucket but not yet a component, exactly.

    Buckets that still hold several components are tied to clusters, so that a document
    belongs to one. The documents outside a cluster's largest component meet each other
    and the rest in blocks of a bounded size; full sets go to block pairs, not to pairs.
    """
    at = labels.select(F.col("node").alias("id"), "root")
    open_ = cells.select("id", "key").join(at, "id")
    lead = open_.groupBy("key").agg(F.min("id").alias("lead"), F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo <> hi").select("key", "lead")
    tied = components(open_.join(lead, "key").select(F.col("id").alias("a"), F.col("lead").alias("b")))
    member = stored(tied.select(F.col("node").alias("id"), F.col("root").alias("cluster")).join(at, "id"), "mh-clusters")
    size = member.groupBy("cluster", "root").agg(F.count("*").alias("m"))
    main = size.groupBy("cluster").agg(F.max(F.struct("m", "root")).alias("main"), F.sum("m").alias("all"))
    count = lambda n: F.greatest(F.ceil(n / BLOCK), F.lit(1)).cast("int")
    one = member.join(main, "cluster").select(
        "id", "root", "cluster", (F.col("root") == F.col("main.root")).alias("in_main"), count(F.col("main.m")).alias("km"), count(F.col("all") - F.col("main.m")).alias("kr")
    ).withColumn("own", F.pmod(F.xxhash64("id"), F.when(F.col("in_main"), F.col("km")).otherwise(F.col("kr"))).cast("int"))
    upto = lambda k: F.sequence(F.lit(0), F.col(k) - 1)
    to = lambda kind, i, j, side: F.struct(F.lit(kind).alias("kind"), i.alias("i"), j.alias("j"), side.alias("side"))
    own, zero, first = F.col("own"), F.lit(0), F.lit(1)
    others = F.transform(upto("kr"), lambda j: to(0, F.least(own, j), F.greatest(own, j), F.when(own > j, first).otherwise(zero)))
    outside = F.concat(others, F.transform(upto("km"), lambda j: to(1, own, j, zero)))
    inside = F.transform(upto("kr"), lambda i: to(1, i, own, first))
    sent = one.select("id", "root", "cluster", F.explode_outer(F.when(F.col("in_main"), inside).otherwise(outside)).alias("t")).select("id", "root", "cluster", "t.*")
    full = sent.join(items, "id")
    return stored_lean(full.groupBy("cluster", "kind", "i", "j").applyInArrow(_blocks(percent), "a long, b long"), "mh-links")


def near_duplicates(docs: DataFrame, percent: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every row of docs.

    percent: least shared share of the union, in hundredths.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    signed = stored_lean(signatures(docs), "mh-signed")
    full = signed.where("n_shingles > 0 and doc_id is not null")
    # classes of equal sets; an id that has several sets names none of them and ties them
    several = stored(full.select("doc_id", "f1", "f2").distinct().groupBy("doc_id").agg(F.count("*").alias("sets")).where("sets > 1").select("doc_id", F.lit(True).alias("many")), "mh-several")
    named = full.join(several, "doc_id", "left").withColumn("own", F.when(F.col("many"), F.xxhash64("f1", "f2")).otherwise(F.col("doc_id")))
    classes = named.groupBy("f1", "f2").agg(
        F.min("own").alias("id"), F.min(F.struct("doc_id", "th")).alias("rep"), F.first("bands").alias("bands"), F.first("packed").alias("packed"), F.first("n_shingles").alias("n")
    )
    classes = stored(classes, "mh-classes")
    sets = full.join(several, "doc_id").select("doc_id", "f1", "f2").distinct().join(classes.select("f1", "f2", "id"), ["f1", "f2"])
    tied = sets.join(sets.groupBy("doc_id").agg(F.min("id").alias("a")), "doc_id").select("a", F.col("id").alias("b")).where("a <> b")

    cells = classes.select("id", "n", "packed", F.posexplode("bands").alias("band", "key"))
    shared = cells.groupBy("key").agg(F.count("*").alias("m"), F.min(F.struct(F.xxhash64("id"), "id"))["id"].alias("lead")).where("m > 1")
    cells = stored(cells.join(shared.select("key"), "key", "left_semi"), "mh-cells")
    active = classes.select("id", "rep.*").join(cells.select("id").distinct(), "id", "left_semi")
    texts = docs.withColumn("th", F.xxhash64("text")).join(active, ["doc_id", "th"]).dropDuplicates(["id"])
    items = stored_lean(texts.select("id", "text").mapInArrow(lean(_sets), "id long, items binary"), "mh-sets")
    likely = percent / 100 - 0.24  # 4.5 standard deviations of the estimate at the threshold

    def confirmed(pairs: DataFrame) -> DataFrame:
        side = lambda c: items.select(F.col("id").alias(c), F.col("items").alias("items_" + c))
        joined = pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "items_a", "items_b")
        return stored_lean(joined.mapInArrow(lean(_confirm(percent)), "a long, b long"), "mh-links")

    def could(p: str, q: str, np: str, nq: str) -> Column:
        sizes = 100 * F.least(np, nq) >= percent * F.greatest(np, nq)
        return sizes & (estimate(F.col(p), F.col(q)) >= likely)

    labels = stored(classes.select(F.col("id").alias("node"), F.col("id").alias("root")), "mh-labels")

    def merged(labels: DataFrame, links: DataFrame) -> DataFrame:
        at = lambda c: labels.select(F.col("node").alias(c), F.col("root").alias(c + "_r"))
        up = links.join(at("a"), "a").join(at("b"), "b").select(F.col("a_r").alias("a"), F.col("b_r").alias("b"))
        roots = components(up)
        return stored(labels.join(roots.select(F.col("node").alias("root"), F.col("root").alias("to")), "root", "left").select("node", F.coalesce("to", "root").alias("root")), "mh-labels")

    labels = merged(labels, tied)
    for step in range(STAR_ROUNDS):
        labelled = cells.join(labels.select(F.col("node").alias("id"), "root"), "id")
        order = F.struct(F.xxhash64("id", F.lit(step)).alias("h"), "id", "root", "n", "packed")
        lead = labelled.groupBy("key").agg(F.min(order).alias("lead"), F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo <> hi").select("key", "lead")
        met = labelled.join(lead, "key").where(F.col("root") != F.col("lead.root")).select(F.col("id").alias("b"), F.col("lead.id").alias("a"), F.col("packed").alias("q"), F.col("lead.packed").alias("p"), F.col("n").alias("nq"), F.col("lead.n").alias("np"))
        labels = merged(labels, confirmed(met.where(could("p", "q", "np", "nq")).select("a", "b").distinct()))

    labels = merged(labels, _rest(cells, labels, items, percent))

    of_class = classes.select("f1", "f2", "id", F.col("rep.doc_id").alias("least")).join(labels.select(F.col("node").alias("id"), "root"), "id")
    smallest = of_class.groupBy("root").agg(F.min("least").alias("component_id"))
    of_class = of_class.join(smallest, "root").select("f1", "f2", "component_id")
    one = signed.join(of_class, ["f1", "f2"], "left")
    component = F.when(F.col("n_shingles") > 0, F.coalesce("component_id", "doc_id")).otherwise(F.col("doc_id"))
    return one.select("doc_id", "n_shingles", F.when(F.col("doc_id").isNotNull(), component).alias("component_id")).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def one_of_each(docs: DataFrame, percent: int = 80) -> DataFrame:
    """The rows of docs whose document stays: one document of each group."""
    gone = stored(near_duplicates(docs, percent).groupBy("doc_id").agg(F.max("kept").alias("kept")).where(~F.col("kept")).select("doc_id"), "mh-gone")
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)
