"""Secrets in texts: candidates by shape, a random forest against false positives.

A candidate is any run in a token of at least LEAST characters of the alphabet that keys
are written in, a digit among them, or any value, of whatever length and characters, that
is assigned to a named secret in the token or by the tokens before it. Its features are its length, how often the kind of
character changes, shares of digits, capitals and hexadecimal digits, how much of its
letters a dictionary of the corpus's frequent words covers, whether it sits in a path or
address, and whether the token itself or its neighbours name a secret. The forest is
trained on labelled findings: given ones, or else those that `rule_findings` labels by
provider formats and by assignments to a named secret; named values that are neither
key-like nor of the dictionary's words are left unlabelled, for the forest to score. Only DataFrame functions and the
JVM's random forest are used.

The findings used are at most `train_rows` of either label, lowest by hash; the
dictionary is the `dictionary_words` most frequent words of all texts.

Defined results: null texts hold no candidate; null ids are kept; repeated rows have
their candidates each; a token with several candidates has a row for each; where findings of one label only exist, the rule's own answer is
the score; an empty table gives no row.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

LEAST = 12
NAMES = "pass(word|wd|phrase)?|pwd|secret|token|api[_-]?key|apikey|access[_-]?key|auth|credential|private[_-]?key"
ASSIGNED = f"(?i)(?:{NAMES})[\"']?\\s*[:=]+>?"
VALUE = r"[^\s\"'&,;<>{}()]+"
PROVIDERS = r"^(AKIA|ASIA)[A-Z0-9]{16}$|^gh[pousr]_[A-Za-z0-9]{36}|^xox[abpr]-[A-Za-z0-9-]{10,}|^sk_live_[A-Za-z0-9]{16,}|^AIza[A-Za-z0-9_-]{35}"
FEATURES = ("length", "changes", "digits", "capitals", "hexadecimal", "covered", "in_path", "named_self", "named_before", "named_near", "quoted", "mail_or_host")


def candidates(docs: DataFrame) -> DataFrame:
    """doc_id, token_no, token, body, before, after of every candidate of every text."""
    texts = docs.where(F.col("text").rlike("[0-9]") | F.col("text").rlike(ASSIGNED))
    t = texts.select(F.col("doc_id").cast("long").alias("doc_id"), F.split("text", r"\s+").alias("t"))
    # the mark of an assignment is in the token or ends one of the two before it
    at = F.expr(f"filter(sequence(0, size(t) - 1), i -> (length(t[i]) >= {LEAST} and t[i] rlike '[0-9]') or t[i] rlike '[:=]' or get(t, i - 1) rlike '[:=]>?$')")
    one = t.withColumn("at", at).select("doc_id", F.explode_outer("at").alias("token_no"), "t").where("token_no is not null").select(
        "doc_id", "token_no", F.expr("t[token_no]").alias("token"), F.expr("concat_ws(' ', slice(t, greatest(token_no - 1, 1), least(token_no, 2)))").alias("before"), F.expr("coalesce(get(t, token_no + 1), '')").alias("after")
    )
    runs = F.filter(F.regexp_extract_all("token", F.lit(r"([A-Za-z0-9+/_\-]{" + str(LEAST) + r",}={0,2})"), F.lit(1)), lambda x: x.rlike("[0-9]"))
    inside = F.regexp_extract_all("token", F.lit(f"{ASSIGNED}[\"']?({VALUE})"), F.lit(2))
    ahead = F.when(F.col("before").rlike(f"{ASSIGNED}$"), F.regexp_extract("token", f"^[\"'(]*({VALUE})", 1)).otherwise("")
    values = F.filter(F.transform(F.concat(inside, F.array(ahead)), lambda x: F.regexp_replace(x, "[.]+$", "")), lambda x: x != "")
    # explode_outer: each list is computed once
    both = one.withColumn("found", F.explode_outer(F.array(F.struct(runs.alias("runs"), values.alias("given")))))
    alone = F.filter("found.runs", lambda r: ~F.exists("found.given", lambda v: F.contains(v, r)))
    bodies = F.array_distinct(F.concat("found.given", alone))
    return both.select("doc_id", "token_no", "token", "before", "after", F.explode_outer(bodies).alias("body")).where("body is not null")


def dictionary(docs: DataFrame, words: int = 2000) -> list[str]:
    """The most frequent words of four letters or more of all texts."""
    w = docs.select(F.explode_outer(F.split(F.lower("text"), r"[^\p{L}]+")).alias("w")).where(F.length("w") >= 4)
    return [r["w"] for r in w.groupBy("w").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "w").limit(words).collect()]


def _share(body: Column, keep: str) -> Column:
    return F.length(F.regexp_replace(body, f"[^{keep}]", "")) / F.length(body)


def features(found: DataFrame, words: list[str]) -> DataFrame:
    body = F.col("body")
    kinds = body
    for kind, mark in (("[+/_=-]", "\u0004"), ("[a-z]", "\u0001"), ("[A-Z]", "\u0002"), ("[0-9]", "\u0003")):
        kinds = F.regexp_replace(kinds, kind, mark)
    runs = F.length(F.regexp_replace(kinds, F.lit("(.)\\1+"), F.lit("$1")))
    pieces = F.filter(F.split(F.lower(body), "[^a-z]+"), lambda x: F.length(x) >= 4)
    listed = F.filter(pieces, lambda x: x.isin(words)) if words else F.array()
    head = F.expr("substring_index(token, body, 1)")
    yes = lambda c: c.cast("double")
    return found.withColumns({
        "length": F.length(body).cast("double"), "changes": (runs - 1) / F.length(body), "digits": _share(body, "0-9"), "capitals": _share(body, "A-Z"),
        "hexadecimal": _share(body, "0-9a-fA-F"), "covered": F.length(F.array_join(listed, "")) / F.length(body), "in_path": yes(F.col("token").rlike(r"[/\\]|^www|^https?:")),
        "named_self": yes(F.lower(head).rlike(f"({NAMES})[\"']?[:=][^a-z0-9&,;]*$")), "named_before": yes(F.lower("before").rlike(f"({NAMES})[\"']?\\s*[:=]?\\s*$|({NAMES})\\s*[:=]")),
        "named_near": yes(F.lower("after").rlike(NAMES)), "quoted": yes(F.col("token").rlike("[\"'].*[\"']")), "mail_or_host": yes(F.col("token").rlike(r"@|^\d+\.\d+\.\d+\.\d+|\.[a-z]{2,4}$")),
    })


def rule_findings(feats: DataFrame) -> DataFrame:
    """Adds label: 1 for provider formats and named assignments of key-like bodies or of six characters with digits among others, null for other named ones outside the dictionary, 0 for the rest."""
    named = (F.col("named_self") + F.col("named_before")) > 0
    key_like = (F.col("length") >= 14) & (F.col("changes") >= 0.15) & (F.col("covered") < 0.4)
    short = (F.col("length") >= 6) & (F.col("digits") > 0) & (F.col("digits") < 1) & (F.col("covered") < 0.4)
    sure = F.col("body").rlike(PROVIDERS) | (named & (key_like | short))
    return feats.withColumn("label", F.when(sure, 1.0).when(named & (F.col("covered") < 0.4), F.lit(None).cast("double")).otherwise(0.0))


def find_secrets(docs: DataFrame, labelled: DataFrame | None = None, train_rows: int = 4000, dictionary_words: int = 2000, trees: int = 24, depth: int = 6) -> DataFrame:
    """doc_id, token_no, body, score (0 to 1) of every candidate.

    labelled: findings with doc_id, token_no and label (0 or 1) to learn from.
    """
    from pyspark.ml.classification import RandomForestClassifier
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.functions import vector_to_array

    from pairmatch.llm.common import stored

    feats = stored(features(candidates(docs), dictionary(docs, dictionary_words)), "secret-candidates")
    known = rule_findings(feats) if labelled is None else feats.join(labelled.select("doc_id", "token_no", F.col("label").cast("double")), ["doc_id", "token_no"])
    known = known.where("label in (0, 1)")
    pick = lambda y: known.where(F.col("label") == y).select(*FEATURES, "label").orderBy(F.xxhash64("body"), "body").limit(train_rows)
    known = known.select(*FEATURES, "label", "body")
    train = stored(pick(0.0).unionByName(pick(1.0)), "secret-training")
    labels = [r["label"] for r in train.select("label").distinct().collect()]
    if len(labels) < 2:
        return rule_findings(feats).select("doc_id", "token_no", "body", F.coalesce("label", F.lit(0.0)).alias("score"))
    join = VectorAssembler(inputCols=list(FEATURES), outputCol="features")
    forest = RandomForestClassifier(numTrees=trees, maxDepth=depth, seed=7, featuresCol="features", labelCol="label").fit(join.transform(train))
    scored = forest.transform(join.transform(feats))
    return scored.select("doc_id", "token_no", "body", vector_to_array("probability")[1].alias("score"))
