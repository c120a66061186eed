"""A counting backbone for the cloze: label-word scores of pairs by log-linear evidence.

A pair becomes a few integer evidence tokens (bucketed word overlap, containment, length
ratio, agreement of numbers, shared long words, overlap in the template's window around
the slot). A word's score at the slot is its log share plus, for each evidence token,
the log of how often the two were seen together: in pretext pairs made from plain
documents, and, after tuning, in labelled pairs. Scores are integer micro-nats, so that
ranks do not depend on the engine. The model has WORDS x EVIDENCE cells whatever the
data; it is collected and goes into the plan as literals.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from pairmatch.functions.templates import Verbalizer
from pairmatch.plans.dialect import spark_sql
from pairmatch.plans.session import cut, put_down

WORDS = Verbalizer.general().vocabulary
EVIDENCE = 112
LABEL_WEIGHT = 10
PASSES = 10

CLEAN = "KEEP(w, TOK({0}), w <> 'col' and w <> 'val')"
NUMBERS = "KEEP(w, {0}, NUM(w))"
LONG = "KEEP(w, {0}, length(w) >= 5)"
ENDS = {"t1": ("TAIL(lt, 3)", "TAIL(rt, 3)"), "t2": ("TAIL(lt, 3)", "HEAD(rt, 3)")}


def evidence_list(template: str = "t2") -> list[str]:
    """Expressions over token lists lt and rt."""
    common, either = "COMMON(lt, rt)", "greatest(EITHER(lt, rt), 1)"
    a, b = ENDS[template]
    numbers = f"EITHER({NUMBERS.format('lt')}, {NUMBERS.format('rt')})"
    return [
        f"DIV({common} * 10, {either})",
        f"16 + DIV({common} * 10, greatest(least(LEN(DISTINCT(lt)), LEN(DISTINCT(rt))), 1))",
        "32 + DIV(least(LEN(lt), LEN(rt)) * 10, greatest(LEN(lt), LEN(rt), 1))",
        f"48 + case when {numbers} = 0 then 9 else DIV(COMMON({NUMBERS.format('lt')}, {NUMBERS.format('rt')}) * 5, greatest({numbers}, 1)) end",
        f"64 + least(COMMON({LONG.format('lt')}, {LONG.format('rt')}), 8)",
        f"80 + COMMON({a}, {b})",
    ]


def with_evidence(df: DataFrame, template: str = "t2") -> DataFrame:
    """Adds ev (array<int>) from left_seq and right_seq."""
    toks = df.withColumns({"lt": F.expr(spark_sql(CLEAN.format("left_seq"))), "rt": F.expr(spark_sql(CLEAN.format("right_seq")))})
    return toks.withColumn("ev", F.array(*[F.expr(spark_sql(e)).cast("int") for e in evidence_list(template)])).drop("lt", "rt")


CLASSES = ("nl", "ns", "pl", "ps")  # with a digit or none; long or short


def features(df: DataFrame, tokens: dict[str, str]) -> DataFrame:
    """Adds a struct a name from an expression of its token list: what evidence needs of one record.

    Its distinct tokens are in four classes apart (numbers or not, long or not), as
    arrays; so a pair needs no more than the sizes of intersections, and a record is cut
    into tokens once, not once a pair, and each token looked at once for digits.
    """
    t = df.withColumns({f"t_{n}": F.expr(spark_sql(e)) for n, e in tokens.items()}).withColumns({f"d_{n}": F.array_distinct(f"t_{n}") for n in tokens})
    t = t.withColumns({f"x_{n}": F.expr(spark_sql(NUMBERS.format(f"d_{n}"))) for n in tokens}).withColumns({f"y_{n}": F.array_except(f"d_{n}", f"x_{n}") for n in tokens})
    size = lambda e, c: F.expr(spark_sql(f"LEN({e})")).alias(c)
    part = lambda c, n: F.expr(spark_sql(f"KEEP(w, {'x' if c[0] == 'n' else 'y'}_{n}, length(w) {'>=' if c[1] == 'l' else '<'} 5)")).alias(c)
    one = lambda n: F.struct(size(f"t_{n}", "n"), size(f"d_{n}", "d"), size(f"x_{n}", "numbers"), *[part(c, n) for c in CLASSES], *[F.expr(spark_sql(f"{e}(t_{n}, 3)")).alias(e) for e in ("HEAD", "TAIL")])
    return t.withColumns({n: one(n) for n in tokens}).drop(*[f"{x}_{n}" for x in "tdxy" for n in tokens])


def paired_evidence(df: DataFrame, left: str, right: str, template: str = "t2") -> DataFrame:
    """Adds ev from the features of both sides, the same as with_evidence has from their texts."""
    both = lambda a, b: F.when(F.size(a) == 0, F.when(F.col(b).isNotNull(), 0)).when(F.size(b) == 0, F.when(F.col(a).isNotNull(), 0)).otherwise(F.size(F.array_intersect(a, b)))
    a, b = (x[:4] for x in ENDS[template])
    met = df.withColumns({f"c_{c}": both(f"{left}.{c}", f"{right}.{c}") for c in CLASSES} | {"c_ends": both(f"{left}.{a}", f"{right}.{b}")})
    met = met.withColumn("c_all", F.expr(" + ".join(f"c_{c}" for c in CLASSES)))
    numbers = f"({left}.numbers + {right}.numbers - c_nl - c_ns)"
    each = [
        f"c_all * 10 div greatest({left}.d + {right}.d - c_all, 1)",
        f"16 + c_all * 10 div greatest(least({left}.d, {right}.d), 1)",
        f"32 + least({left}.n, {right}.n) * 10 div greatest({left}.n, {right}.n, 1)",
        f"48 + case when {numbers} = 0 then 9 else (c_nl + c_ns) * 5 div greatest({numbers}, 1) end",
        "64 + least(c_nl + c_pl, 8)",
        "80 + c_ends",
    ]
    return met.withColumn("ev", F.array(*[F.expr(e).cast("int") for e in each])).drop("c_all", "c_ends", *[f"c_{c}" for c in CLASSES])


def evidence_of(pairs: DataFrame, left: DataFrame, right: DataFrame, template: str = "t2") -> DataFrame:
    """pairs (left_id, right_id) with ev, from the sequences (id, seq) of both sides."""
    side = lambda x, n: features(x, {n: CLEAN.format("seq")}).select(F.col("id").alias(f"{n}_id"), n)
    met = pairs.join(side(left, "left"), "left_id").join(side(right, "right"), "right_id")
    return paired_evidence(met, "left", "right", template).drop("left", "right")


PART_PAIRS, PARTS = 1_000_000, 8  # pairs that are joined with their records at once, if that makes no more parts than these


def stored_evidence(pairs: DataFrame, left: DataFrame, right: DataFrame, keep: list[str], template: str = "t2") -> DataFrame:
    """evidence_of as a stored table, columns keep and ev.

    A pair takes the tokens of both its records through the joins, so pairs go in parts,
    by a hash of their left record, and what a part shuffled goes before the next one:
    the disk in use is that of the records and of one part. Parts are few, for each
    shuffles all right records again.
    """
    side = lambda x, n: put_down(features(x, {n: CLEAN.format("seq")}).select(F.col("id").alias(f"{n}_id"), n), f"tokens-{n}")
    a, b, p = side(left, "left"), side(right, "right"), put_down(pairs, "pairs")
    parts, out = min(PARTS, max(1, -(-p.count() // PART_PAIRS))), None
    for i in range(parts):
        own = F.pmod(F.xxhash64("left_id"), F.lit(parts)) == i
        met = p.where(own).join(a.where(own), "left_id").join(b, "right_id")
        one = put_down(paired_evidence(met, "left", "right", template).select(*keep, "ev"), "evidence")
        out = one if out is None else out.unionByName(one)
    return out


_DOCS = "select doc_id, TOK(text) as t from {documents}"
PRETEXT = f"""
select word, lt, rt from (
  select 0 as word, HEAD(t, 40) as lt, HEAD(t, 40) as rt from ({_DOCS}) p0 where LEN(t) >= 20
  union all select 1, HEAD(t, 40), KEEPI(w, i, HEAD(t, 40), H('pre|' || STR(doc_id) || '|' || STR($i)) % 100 >= 30) from ({_DOCS}) p1 where LEN(t) >= 20
  union all select 2, HEAD(t, 40), FROM(t, 21, 40) from ({_DOCS}) p2 where LEN(t) >= 20
  union all select 3, HEAD(a.t, 40), HEAD(b.t, 40) from ({_DOCS}) a join ({_DOCS}) b on b.doc_id = a.doc_id + 1 where LEN(a.t) >= 20 and LEN(b.t) >= 20
  union all select 4, HEAD(a.t, 40), FROM(b.t, 21, 40) from ({_DOCS}) a join ({_DOCS}) b on b.doc_id = a.doc_id + 1 where LEN(a.t) >= 20 and LEN(b.t) >= 20
  union all select 5, HEAD(a.t, 40), HEAD(b.t, 40) from ({_DOCS}) a join ({_DOCS}) b on b.doc_id = a.doc_id + 7 where LEN(a.t) >= 20 and LEN(b.t) >= 20
) u_"""


def pretext_counts(spark: SparkSession, d: str, template: str = "t2") -> DataFrame:
    """word, f, n from label-free pairs of documents."""
    # each variant is a feature of a document; only as many tokens as they take are cut off a text, once:
    # a filter does not pass below an explode, where the cut would be made for it and again for the rows
    words = "filter(slice(split(lower(text), '[^\\\\p{L}\\\\p{N}]+', 62), 1, 61), w_ -> w_ <> '')"
    docs = spark.read.parquet(f"{d}/documents.parquet").select("doc_id", F.expr(words).alias("w")).select("doc_id", F.explode(F.array(F.expr("slice(w, 1, 60)"))).alias("t")).where("size(t) >= 20")
    drop = "KEEPI(w, i, HEAD(t, 40), H('pre|' || STR(doc_id) || '|' || STR($i)) % 100 >= 30)"
    t = cut(features(docs, {"a": "HEAD(t, 40)", "k": drop, "f": "FROM(t, 21, 40)"}).select("doc_id", "a", "k", "f"))
    near = lambda n, x: t.select(F.col("doc_id").alias("_i"), "a").join(t.select((F.col("doc_id") - n).alias("_i"), F.col(x).alias("_b")), "_i").select(F.col("a").alias("lt"), F.col("_b").alias("rt"))
    own = lambda x: t.select(F.col("a").alias("lt"), F.col(x).alias("rt"))
    out = None
    for i, rows in enumerate((own("a"), own("k"), own("f"), near(1, "a"), near(1, "f"), near(7, "a"))):
        one = rows.select(F.lit(i).alias("word"), "lt", "rt")
        out = one if out is None else out.unionByName(one)
    ev = paired_evidence(out, "lt", "rt", template)
    return ev.groupBy("word", "ev").agg(F.count("*").alias("m")).select("word", F.explode("ev").alias("f"), "m").groupBy("word", "f").agg(F.sum("m").alias("n"))


def label_counts(labelled: DataFrame, verb: Verbalizer | None = None) -> DataFrame:
    """word, f, n of labelled pairs (ev, y): each counts for all words of its class."""
    verb = verb or Verbalizer.general()
    at = lambda ws: F.array(*[F.lit(WORDS.index(w)) for w in ws])
    each = labelled.select(F.explode(F.when(F.col("y") == 1, at(verb.yes)).otherwise(at(verb.no))).alias("word"), "ev")
    return each.select("word", F.explode("ev").alias("f")).groupBy("word", "f").agg((F.count("*") * LABEL_WEIGHT).alias("n"))


@dataclass(frozen=True)
class CountModel:
    """weights[word][evidence] and prior[word] in micro-nats."""

    weights: tuple[tuple[int, ...], ...]
    prior: tuple[int, ...]
    verb: Verbalizer = Verbalizer()

    @staticmethod
    def _row(values) -> Column:
        """A constant array as one small foldable expression."""
        return F.split(F.lit(",".join(map(str, values))), ",").cast("array<bigint>")

    def _with_words(self, df: DataFrame, kept=None) -> DataFrame:
        """Adds word_e from ev; kept(i) says whether evidence i counts.

        Scores are columns of their own and no lambda reads them, so that none is computed twice.
        """
        sums = {}
        for w in range(len(WORDS)):
            total, row = F.lit(self.prior[w]).cast("bigint"), self._row(self.weights[w])
            for i in range(len(evidence_list())):
                cell = F.get(row, F.col("ev")[i])
                total = total + (cell if kept is None else F.when(kept(i), cell).otherwise(0))
            sums[f"_s{w}"] = total
        scored = df.withColumns(sums).withColumn("_top", F.greatest(*sums))
        return scored.withColumn("word_e", F.array(*[F.exp((F.col(c) - F.col("_top")) / F.lit(1e6)) for c in sums])).drop("_top", *sums)

    def _yes_share(self, e: Column) -> Column:
        mean = lambda ws: sum((e[WORDS.index(w)] for w in ws[1:]), e[WORDS.index(ws[0])]) / len(ws)
        yes, no = mean(self.verb.yes), mean(self.verb.no)
        return yes / (yes + no)

    def with_words(self, df: DataFrame) -> DataFrame:
        """Adds word_e: the words' unnormalised probabilities at the slot, the best being 1."""
        return self._with_words(df)

    def score(self, df: DataFrame) -> DataFrame:
        """Adds p_yes (rounded to 6 digits), pred and conf."""
        p = self.with_words(df).withColumn("p_yes", F.round(self._yes_share(F.col("word_e")), 6)).drop("word_e")
        return p.withColumn("pred", (F.col("p_yes") > 0.5).cast("int")).withColumn("conf", F.greatest("p_yes", F.round(1 - F.col("p_yes"), 6)))

    def passes(self, df: DataFrame, n: int = PASSES, seed: int = 0) -> DataFrame:
        """Adds p_passes: P(yes) with evidence tokens left out at random, n times.

        A token is left out in 5 of 16 cases, by a digit of a hash of (pair, pass), so
        results depend neither on partitions nor on retries.
        """
        # P(yes) depends on the evidence and on which of its tokens count: one table of all 64 choices for each list
        m = len(evidence_list())
        code = sum((F.coalesce(F.col("ev")[i], F.lit(EVIDENCE)) * F.lit((EVIDENCE + 1) ** i).cast("bigint") for i in range(1, m)), F.coalesce(F.col("ev")[0], F.lit(EVIDENCE)).cast("bigint"))
        lists = df.select(code.alias("_code"), "ev").dropDuplicates(["_code"]).withColumn("_mask", F.explode(F.sequence(F.lit(0), F.lit(2**m - 1))))
        scored = self._with_words(lists, lambda i: F.col("_mask").bitwiseAND(1 << (m - 1 - i)) > 0)
        shares = scored.select("_code", F.struct("_mask", F.round(self._yes_share(F.col("word_e")), 6).alias("p")).alias("_p")).groupBy("_code").agg(F.array_sort(F.collect_list("_p"))["p"].alias("_shares"))
        # a digit of 5 or more keeps its token: six digits become six bits, the first token's the highest
        digits = lambda k: F.substring(F.md5(F.concat_ws("|", F.lit(f"drop{seed}"), F.col("pair_id"), F.lit(str(k)))), 1, m)
        mask = lambda k: F.conv(F.translate(digits(k), "0123456789abcdef", "0" * 5 + "1" * 11), 2, 10).cast("int")
        masked = df.withColumns({f"_m{k}": mask(k) for k in range(n)} | {"_code": code})
        met = masked.join(shares, "_code")
        return met.withColumn("p_passes", F.array(*[F.get("_shares", F.col(f"_m{k}")) for k in range(n)])).drop("_code", "_shares", *[f"_m{k}" for k in range(n)])


def model_of(counts: DataFrame, verb: Verbalizer | None = None) -> CountModel:
    """From (word, f, n) rows, summed if a cell comes more than once."""
    import math

    cells = {(r["word"], r["f"]): r["n"] for r in counts.groupBy("word", "f").agg(F.sum("n").alias("n")).collect()}  # at most WORDS x EVIDENCE
    log = lambda x: round(math.log(x) * 1e6)
    totals = [sum(n for (w, _), n in cells.items() if w == i) for i in range(len(WORDS))]
    weights = tuple(tuple(log((cells.get((w, f), 0) + 1.0) / (totals[w] + float(EVIDENCE))) for f in range(EVIDENCE)) for w in range(len(WORDS)))
    prior = tuple(log((t + 1.0) / (sum(totals) + float(len(WORDS)))) for t in totals)
    return CountModel(weights, prior, verb or Verbalizer.general())


def tuned(pretext: DataFrame, labelled: DataFrame, verb: Verbalizer | None = None) -> CountModel:
    return model_of(pretext.unionByName(label_counts(labelled, verb)), verb)
