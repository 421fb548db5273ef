"""Secret scanning: high-recall candidates, and a random forest that removes the false positives.

Candidates are values assigned to a credential word and runs of key characters with digits. Features are the
candidate's length, character classes and transitions, how much of it common words cover, the path, and neighbouring words. The forest is
fitted on the driver from labelled findings and runs as SQL expressions over arrays inside each row.

The dictionary is the letter groups of all words of the table. Labelled findings are of two sources: long numbers and number-like runs found in all documents
away from any credential word are false ones, alike ones counted as one row with a weight; keys, tokens and passwords, and hashes, identifiers and placeholders, made from format rules and set
into contexts and paths of the same documents, are both.
"""

from __future__ import annotations

import random

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from netjoin.llm import trees
from netjoin.llm.common import text_or_empty
from netjoin.llm.spans import contexts_of, inline_rows, matches, quoted

_WORD = "(?:password|passwd|passphrase|pwd|secret|token|api[_-]?key|access[_-]?key|private[_-]?key|credential|auth)"
_RUN = "A-Za-z0-9+/_"
ASSIGNED = rf"(?i:(?<![A-Za-z]){_WORD}[\x22']?\x20{{0,3}}[:=]\x20{{0,3}}[\x22']?[^\x20\x09-\x0D\x22'<>]{{6,}}+)"
RUN = rf"(?<![{_RUN}])(?=[A-Za-z+/_]*+[0-9])[{_RUN}]{{16,}}+=*+"
PATTERN = f"{ASSIGNED}|{RUN}"
_HEAD = rf"^(?i:{_WORD}[\x22']?\x20{{0,3}}[:=]\x20{{0,3}}[\x22']?)"
# Words of placeholders.
FAKE = ("example", "sample", "change", "dummy", "fake", "placeholder", "your", "here", "test", "xxxx", "redacted", "foo", "bar", "user", "default", "required")
FEATURES = ("n", "n_digit", "n_upper", "n_lower", "n_other", "n_turns", "n_kinds", "covered", "faked", "hex", "digits_only", "assigned", "known_prefix", "path_test", "near_secret", "near_hash", "near_fake", "repeated")
#: Made findings, what all found ones weigh together at most, contexts and paths for made ones, and letter groups of the dictionary.
SAMPLE_ROWS, FOUND_WEIGHT, CONTEXTS, PATHS, DICTIONARY = 2400, 1200, 500, 100, 3000
#: Found findings whose features are equal to so many digits are alike.
DIGITS = 2
#: Letters in a group of the dictionary.
GROUP = 4


def dictionary_of(rows: DataFrame) -> list[str]:
    """The letter groups that most words of most documents hold, in words of letters alone; counted over all rows."""
    words = rows.select(F.explode(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit(r"(?<![\p{L}0-9])\p{L}{4,24}(?![\p{L}0-9])"), F.lit(0)))).alias("w")).groupBy("w").agg(F.count(F.lit(1)).alias("n"))
    groups = words.select(F.explode(F.expr(f"transform(sequence(1, length(w) - {GROUP - 1}), i -> substring(w, i, {GROUP}))")).alias("g"), "n")
    top = groups.groupBy("g").agg(F.sum("n").alias("n")).where("n > 1").orderBy(F.desc("n"), "g").limit(DICTIONARY)
    return sorted(r["g"] for r in top.collect())


def _features(c: str, path: str, known: list[str]) -> str:
    """named_struct of FEATURES; ``c`` is a candidate struct, ``path`` the document's path, ``known`` the dictionary."""
    v = "v"
    held = f"array({', '.join(map(quoted, known))})" if known else "cast(array() AS array<string>)"
    groups = f"transform(sequence(1, greatest(1, length(left({v}, 200)) - {GROUP - 1})), i -> lower(substring({v}, i, {GROUP})))"
    covered = f"transform(array({groups}), gs -> size(filter(gs, g -> array_contains({held}, g))) / size(gs))[0]"
    parts = {
        "n": f"double(least(length({v}), 400))", "n_digit": f"double(regexp_count({v}, '[0-9]')) / length({v})", "n_upper": f"double(regexp_count({v}, '[A-Z]')) / length({v})",
        "n_lower": f"double(regexp_count({v}, '[a-z]')) / length({v})", "n_other": f"double(regexp_count({v}, '[^A-Za-z0-9]')) / length({v})",
        "n_turns": f"double(regexp_count({v}, {quoted('(?<=[a-z])(?=[A-Z0-9])|(?<=[A-Z])(?=[0-9])|(?<=[0-9])(?=[A-Za-z])')})) / length({v})",
        "n_kinds": f"double(size(array_distinct(split(left({v}, 64), '')))) / least(length({v}), 64)", "covered": f"double({covered})", "faked": f"double(regexp_count({v}, {quoted('(?i)(' + '|'.join(FAKE) + ')')}))",
        "hex": f"double({v} RLIKE '^[0-9a-f]+$')", "digits_only": f"double({v} RLIKE '^[0-9]+$')", "assigned": f"double({c}.value RLIKE {quoted(_HEAD)})",
        "known_prefix": f"double({v} RLIKE {quoted('^(AKIA|ASIA|ghp_|gho_|glpat|sk_live|sk-|xox[bp]|AIza|eyJ)')})", "path_test": f"double({path} RLIKE '(?i)(test|example|sample|fixture|doc)')",
        "near_secret": f"double(concat({c}.left, {c}.value) RLIKE {quoted('(?i)' + _WORD)})", "near_hash": f"double(concat({c}.left, ' ', left({c}.right, 12)) RLIKE {quoted('(?i)(sha-?[0-9]|md5|commit|checksum|uuid|digest|hash|revision|etag|://|href)')})",
        "near_fake": f"double(concat({c}.left, {c}.value, {c}.right) RLIKE {quoted('(?i)(example|dummy|fake|placeholder|your[_-]|changeme|xxxx|redacted|<)')})",
        "repeated": f"double({v} RLIKE {quoted('(.)\\1{4}')})",
    }
    made = "named_struct(" + ", ".join(f"'{k}', {x}" for k, x in parts.items()) + ")"
    return f"transform(array(regexp_replace({c}.value, {quoted(_HEAD)}, '')), v -> {made})[0]"


def made_findings(contexts: list[tuple[str, str]], paths: list[str], words: list[str], n: int = SAMPLE_ROWS, seed: int = 11) -> list[dict]:
    """Labelled findings made from format rules: keys, tokens and passwords against hashes, identifiers, numbers and placeholders. Contexts and paths are
    drawn alike for both; words are letter groups."""
    r = random.Random(seed)
    pick = lambda s, k: "".join(r.choice(s) for _ in range(k))
    hexa, upper, alnum, low = "0123456789abcdef", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789", "abcdefghijklmnopqrstuvwxyz"
    wordy = lambda k: "".join(r.choice(words or ["text", "word", "line"]) for _ in range(k))
    head = lambda: r.choice(["password", "token", "secret", "api_key", "Password", "TOKEN", "passwd", "access_key"]) + r.choice(["=", " = ", ": ", ':"', ' = "', "='"])
    case = lambda s: s.upper() if r.random() < 0.15 else s
    good = [
        lambda: (pick("A", 1) + "KIA" + pick(upper, 16), ""), lambda: (head() + case(pick(hexa, r.choice([18, 32, 40, 64]))), ""), lambda: (head() + pick(alnum + "!@#", r.randint(10, 30)), ""),
        lambda: ("ghp_" + pick(alnum, 36), ""), lambda: ("sk_live_" + pick(alnum, 24), ""), lambda: (pick(alnum + "+/", 40), "secret "), lambda: (pick(alnum, 32), "api key "),
    ]
    bad = [
        lambda: (pick(hexa, r.choice([32, 40, 64])), r.choice(["sha256 ", "md5 ", "commit ", "checksum: ", "revision "])), lambda: (pick("0123456789", r.randint(16, 20)), ""),
        lambda: (wordy(2) + "_" + wordy(2) + pick("0123456789", 2) + wordy(1), ""), lambda: (head() + r.choice(["xxxxxxxx", "changeme", "your_password_here", "example123", "<redacted", "********", "required_field"]), ""),
        lambda: (wordy(r.randint(3, 6)) + pick("0123456789", r.randint(1, 4)), ""), lambda: (wordy(2) + "/" + wordy(2) + "/" + pick("0123456789", 3), "https://" + pick(low, 6)),
        lambda: (head() + wordy(r.randint(2, 3)), ""), lambda: (pick(alnum, 24), "uuid "), lambda: (pick("0123456789", 16), "card "),
    ]
    out = []
    for i in range(n):
        label = i % 2
        (value, cue), (before, after) = r.choice(good if label else bad)(), r.choice(contexts)
        out.append({"value": value, "left": (before + cue)[-32:], "right": after[:32], "path": r.choice(paths), "good": label})
    return out


def found_findings(rows: DataFrame) -> DataFrame:
    """value, left, right, path, good = 0: runs in the documents that stand away from credential words and are numbers, or words with numbers."""
    each = rows.where("text RLIKE '[0-9:=]'").select("path", F.explode(matches("text", PATTERN)).alias("c")).select("c.value", "c.left", "c.right", "path", F.lit(0).alias("good"))
    return each.where(~F.concat("left", "value").rlike(f"(?i){_WORD}") & (F.col("value").rlike("^[0-9]+$") | F.col("value").rlike("^[a-z]+[0-9]{1,4}$")))


def weighted_findings(rows: DataFrame, known: list[str]) -> list[tuple[list[float], int, float]]:
    """(features, 0, weight) of all found findings: those alike in their features are one row that weighs their number. The driver holds a row for each kind that occurs, however often."""
    features = F.expr(_features("named_struct('value', value, 'left', left, 'right', right)", "path", known))
    each = found_findings(rows).select(features.alias("f")).select(*(F.round(F.col(f"f.{x}"), DIGITS).alias(x) for x in FEATURES))
    got = [(list(r)[:-1], 0, float(r["weight"])) for r in each.groupBy(*FEATURES).agg(F.count(F.lit(1)).alias("weight")).collect()]
    total = sum(w for *_, w in got)
    return sorted((f, y, w * min(1.0, FOUND_WEIGHT / total)) for f, y, w in got)


def fitted_forest(rows: DataFrame) -> tuple:
    """(trees, threshold, held-out accuracy, dictionary) from the findings in all rows (text, path) and made findings; the same for the same rows.

    Only the contexts and paths that made findings are set into are drawn: the first by a hash, and the most frequent ones.
    """
    spark = rows.sparkSession
    rows = rows.select("text", "path")
    known = dictionary_of(rows)
    paths = sorted(r["path"] for r in rows.groupBy("path").count().orderBy(F.desc("count"), "path").limit(PATHS).collect())
    made = made_findings(contexts_of(rows, CONTEXTS, by_hash=True), [*(paths or ["src"]), "src/app.py", "config/prod.env", "docs/readme.md"], known)
    features = F.expr(_features("named_struct('value', value, 'left', left, 'right', right)", "path", known))
    got = inline_rows(spark, made, "value:string,left:string,right:string,path:string,good:int").select("good", features.alias("f")).collect()
    labelled = sorted((list(r["f"]), r["good"], 1.0) for r in got) + weighted_findings(rows, known)
    random.Random(1).shuffle(labelled)
    x, y, weight = np.array([v[0] for v in labelled], float), np.array([v[1] for v in labelled]), np.array([v[2] for v in labelled])
    train = np.arange(len(x)) % 4 < 3
    forest = trees.fit_forest(x[train], y[train], weight[train], trees=15, depth=7)
    score = np.mean([trees.predict(t, x[~train]) for t in forest], axis=0)
    limit = max(0.5, trees.calibrated_threshold(score, y[~train], 0.98, weight[~train]))
    return tuple(forest), limit, float(np.average((score >= limit) == y[~train], weights=weight[~train])), known


def secret_findings(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", path_col: str | None = "source", model: tuple | None = None) -> DataFrame:
    """doc_id, text, candidates (array of start, end, score) and secrets (those that pass), one row for each row.

    Positions are code points of the whole candidate (with its credential word), end exclusive. Null and empty texts have none; a null path counts
    as empty. Repeated rows are scanned each, texts of any length whole; a null id is passed on, an empty table gives no rows, and other columns are not read.
    """
    path = F.coalesce(F.col(path_col).cast("string"), F.lit("")) if path_col else F.lit("")
    rows = docs.select(F.col(id_col).alias("doc_id"), text_or_empty(text_col).alias("text"), path.alias("path"))
    forest, limit, _, known = model or fitted_forest(rows)
    rows = rows.withColumn("found", F.when(F.col("text").rlike("[0-9:=]"), matches("text", PATTERN)).otherwise(F.expr("cast(array() AS array<struct<start:int,end:int,value:string,left:string,right:string>>)")))
    score = f"({' + '.join(trees._case(t, [f'f.{n}' for n in FEATURES]) for t in forest)}) / {float(len(forest))}D"
    scored = f"transform(found, c -> named_struct('start', c.start, 'end', c.end, 'score', transform(array({_features('c', 'path', known)}), f -> {score})[0]))"
    none = "cast(array() AS array<struct<start:int,end:int,score:double>>)"
    rows = rows.withColumn("candidates", F.expr(f"CASE WHEN size(found) = 0 THEN {none} ELSE {scored} END"))
    return rows.select("doc_id", "text", "candidates", F.expr(f"filter(candidates, c -> c.score >= {limit!r}D)").alias("secrets"))


def secret_digests(docs: DataFrame, **options) -> DataFrame:
    """doc_id, n_candidates, n_secrets, spans (start:end of the secrets, comma-joined)."""
    found = secret_findings(docs, **options).drop("text")
    return found.select("doc_id", F.size("candidates").cast("long").alias("n_candidates"), F.size("secrets").cast("long").alias("n_secrets"), F.expr("array_join(transform(secrets, c -> concat(c.start, ':', c.end)), ',')").alias("spans"))


def mask_secrets(docs: DataFrame, **options) -> DataFrame:
    """doc_id, text with every secret replaced by ``[secret]``."""
    step = "(s, c) -> named_struct('at', c.end, 'out', concat(s.out, substring(text, s.at + 1, c.start - s.at), '[secret]'))"
    return secret_findings(docs, **options).select("doc_id", F.expr(f"aggregate(secrets, named_struct('at', 0, 'out', ''), {step}, s -> concat(s.out, substring(text, s.at + 1)))").alias("text"))
