"""Personal data: base formats by rule, further spans by boosted trees over high-recall candidates.

Base spans (email, ip, card, phone) follow fixed patterns with checks. Generators with high recall propose further spans of other kinds;
features of format and context feed gradient-boosted trees whose probability must pass a calibrated threshold. Of overlapping proposals
the likeliest is selected, and none may overlap a base span. Everything on the main path is a SQL expression over one row's
text: no shuffle, no Python.

The trees are fitted on the driver from a bounded labelled sample of two sources. Candidates of sampled documents of the table itself are labelled by what the
base rules say of the same place: inside a base span of the kin kind they are right; on a base span of another kind, on a run that fails its check, or
after a word that names no credential they are wrong. Examples made from format rules, set into contexts cut from the same documents, cover kinds that the sample lacks.
"""

from __future__ import annotations

import random

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from netjoin.llm import trees
from netjoin.functions.workspace import drop_tables
from netjoin.llm.common import materialise, text_or_empty
from netjoin.llm.spans import contexts_of, inline_rows, matches, quoted, sampled_rows

BASE_KINDS = ("email", "ip", "card", "phone")
# Fixed patterns of the contract, with possessive repeats and starts at the front of a run, so that long runs stay linear.
_LOCAL = "A-Za-z0-9._%+-"
PATTERNS = {
    "email": rf"(?:\G|(?<![{_LOCAL}]))[{_LOCAL}]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: What a text must hold for a pattern to be tried at all.
HINTS = {"email": "@", "ip": ".", "card": "", "phone": "+"}
_PART = "0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9])"
_LUHN = "aggregate(sequence(1, length(d)), 0, (s, i) -> s + CASE WHEN i % 2 = 1 THEN int(substring(d, length(d) - i + 1, 1)) WHEN int(substring(d, length(d) - i + 1, 1)) > 4 THEN 2 * int(substring(d, length(d) - i + 1, 1)) - 9 ELSE 2 * int(substring(d, length(d) - i + 1, 1)) END) % 10 = 0"
CHECKS = {
    "email": "true",
    "ip": f"c.value RLIKE {quoted(rf'^{_PART}(?:[.]{_PART}){{3}}$')}",
    "card": f"exists(array(translate(c.value, ' -', '')), d -> CASE WHEN length(d) BETWEEN 16 AND 19 THEN {_LUHN} ELSE false END)",
    "phone": "length(regexp_replace(c.value, '[^0-9]', '')) BETWEEN 8 AND 15",
}

_SECRET = "(?:password|passwd|passphrase|pwd|secret|token|api[_-]?key|access[_-]?key|private[_-]?key|credential|auth)"
#: Kinds that the method adds, in their order after the base kinds, with their generators.
EXTRA = {
    "email_spelled": r"(?i)(?<![A-Za-z0-9])[a-z0-9._-]{2,40}\x20?[\[(]?\x20?at\x20?[\])]?\x20?[a-z0-9-]{2,40}\x20?[\[(]?\x20?dot\x20?[\])]?\x20?[a-z]{2,10}(?![A-Za-z0-9])",
    "iban": r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?:\x20?[A-Z0-9]{4}){3,7}(?:\x20?[A-Z0-9]{1,3})?(?![A-Za-z0-9])",
    "national_id": r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])",
    "phone_local": r"(?<![0-9+(-])\(?[0-9]{2,4}\)?[\x20.-][0-9]{3,4}[\x20.-]?[0-9]{3,4}(?![0-9-])",
    "credential": r"(?<![A-Za-z0-9_])[A-Za-z][A-Za-z_-]{2,24}[\x22']?\x20{0,3}[:=]\x20{0,3}[\x22']?[^\x20\x09-\x0D\x22'<>]{6,200}+[\x22']?",
}
#: A cheap test before a generator runs.
EXTRA_HINTS = {"email_spelled": r"(?i)dot", "iban": r"[A-Z]{2}[0-9]{2}", "national_id": r"[0-9]-[0-9]{2}-[0-9]", "phone_local": r"[0-9][)\x20.-]{1,2}[0-9]{3}", "credential": r"[A-Za-z][\x22']?\x20{0,3}[:=]"}
#: The base kind that an added kind is a looser form of.
KIN = {"email_spelled": "email", "phone_local": "phone"}
_CUES = {
    "cue_phone": "(?i)(phone|tel|call|fax|mobile|ring|appel|anruf|llam)",
    "cue_id": "(?i)(ssn|social|national|insurance|passport|identit)",
    "cue_mail": "(?i)(mail|contact|write|reach|address)",
    "cue_bank": "(?i)(iban|bank|account|transfer|konto|compte|cuenta)",
    "cue_other": "(?i)(order|invoice|part|item|version|page|isbn|serial|ratio|score|[$%#])",
}
FEATURES = ("kind", "n", "n_digits", "n_seps", "n_upper", "n_turns", "n_kinds", "bracket", "secret_word", "dialled", *_CUES, "hard_left", "hard_right")
#: Bounds of the labelled sample the trees are fitted on: made examples, documents to look for candidates in, and candidates of these.
SAMPLE_ROWS, SAMPLE_DOCS, SAMPLE_FOUND = 2500, 4000, 2500


def _features(kind: str, c: str = "c") -> str:
    """named_struct of FEATURES for a candidate of a kind (its number as SQL)."""
    parts = {
        "kind": f"double({kind})", "n": f"double(length({c}.value))", "n_digits": f"double(regexp_count({c}.value, '[0-9]'))", "n_seps": f"double(regexp_count({c}.value, '[ .-]'))",
        "n_upper": f"double(regexp_count({c}.value, '[A-Z]'))", "bracket": f"double({c}.value RLIKE '[(\\\\[]')",
        "n_turns": f"double(regexp_count({c}.value, {quoted('(?<=[A-Za-z])(?=[0-9])|(?<=[0-9])(?=[A-Za-z])')}))", "n_kinds": f"double(size(array_distinct(split(left({c}.value, 64), ''))))",
        "secret_word": f"double({c}.value RLIKE {quoted('(?i)^[A-Za-z_-]*' + _SECRET)})", "dialled": f"double({c}.left RLIKE {quoted('[+][0-9]{1,3}[ .-]?$')})",
        **{name: f"double({c}.left RLIKE {quoted(cue)})" for name, cue in _CUES.items()},
        "hard_left": f"double({c}.left RLIKE '[0-9A-Za-z]$')", "hard_right": f"double({c}.right RLIKE '^[0-9A-Za-z%]')",
    }
    return "named_struct(" + ", ".join(f"'{k}', {v}" for k, v in parts.items()) + ")"


def made_candidates(contexts: list[tuple[str, str]], n: int = SAMPLE_ROWS, seed: int = 5) -> list[dict]:
    """Labelled candidates of every kind, made from format rules, with and without the cue that makes them personal, in given contexts."""
    r = random.Random(seed)
    pick = lambda s, k: "".join(r.choice(s) for _ in range(k))
    digits, low, alnum = "0123456789", "abcdefghijklmnopqrstuvwxyz", "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789"
    word = lambda: pick("aeinorstlmd", r.randint(3, 9))
    cues = {0: ("mail me: ", "contact ", "reach us at ", "write to "), 1: ("IBAN: ", "bank account ", "transfer to "), 2: ("SSN: ", "social security ", "national id "), 3: ("phone: ", "call ", "tel. ", "fax "), 4: ("", "", "set ", "use ")}
    others = ("order ", "part no. ", "item ", "version ", "invoice ", "score ", "ratio ", "page ")
    key = lambda: r.choice(["password", "token", "secret", "api_key", "Password", "TOKEN", "passwd", "access-key", "auth"])
    sign = lambda: r.choice(["=", " = ", ": ", ":", ' = "', "='"])
    out = []
    for _ in range(n):
        kind, good = r.randrange(len(EXTRA)), r.random() < 0.5
        value = (f"{word()}{r.choice([' at ', ' [at] ', '(at)'])}{word()}{r.choice([' dot ', ' [dot] ', '(dot)'])}{r.choice(['com', 'org', 'net'])}" if good else f"{word()} at {word()} dot {word()[:10]}",
                 pick("DEFRES", 2) + pick(digits, 2) + "".join((" " if good and r.random() < 0.5 else "") + pick(digits, 4) for _ in range(r.randint(3, 5))),
                 f"{pick(digits, 3)}-{pick(digits, 2)}-{pick(digits, 4)}",
                 f"({pick(digits, 3)}) {pick(digits, 3)}-{pick(digits, 4)}" if r.random() < 0.5 else f"{pick(digits, 3)}{r.choice(' .-')}{pick(digits, 3)}{r.choice(' .-')}{pick(digits, 4)}",
                 (key() + sign() + r.choice([pick("0123456789abcdef", r.choice([16, 18, 24, 32, 40, 64])), pick("0123456789ABCDEF", r.choice([18, 40])), pick(alnum, r.randint(12, 40)), pick(alnum + "!#%", r.randint(9, 20))])) if good
                 else r.choice([lambda: key() + sign() + pick("aeinrstlo", r.randint(6, 12)), lambda: word() + sign() + pick(low, r.randint(6, 14)), lambda: word() + sign() + pick(digits, r.randint(6, 16)),
                                lambda: key() + sign() + r.choice(["xxxxxxxx", "changeme", "required", "your_password", "********"]), lambda: "http:" + "//" + pick(low, 8) + "/" + pick(alnum, 9), lambda: word() + sign() + pick(alnum, r.randint(8, 24))])())[kind]
        before, after = r.choice(contexts)
        left = before + (r.choice(cues[kind]) if good else (r.choice(others) if r.random() < 0.6 else "") if kind < 4 else "")
        out.append({"kind": kind, "value": value, "left": left[-32:], "right": after[:32], "good": int(good)})
    return out


def found_candidates(rows: DataFrame) -> DataFrame:
    """kind (number), value, left, right, good: candidates of the rows' texts where the base rules settle what they are."""
    span = "named_struct('kind', '{k}', 'start', c.start, 'end', c.end, 'fine', {check})"
    matched = rows.select("text", *(matches("text", PATTERNS[k]).alias(f"b_{k}") for k in BASE_KINDS), *(matches("text", p).alias(f"x{i}") for i, p in enumerate(EXTRA.values())))
    told = matched.withColumn("told", F.expr("concat(" + ", ".join(f"transform(b_{k}, c -> {span.format(k=k, check='coalesce(' + CHECKS[k] + ', false)')})" for k in BASE_KINDS) + ")"))
    out = None
    for i, kind in enumerate(EXTRA):
        on = "filter(told, b -> b.start < c.end AND c.start < b.end)"
        kin = f"exists({on}, b -> b.fine AND b.kind = '{KIN.get(kind, '')}')"
        other = f"c.value NOT RLIKE {quoted('(?i)^[A-Za-z_-]*' + _SECRET)}" if kind == "credential" else f"size({on}) > 0"
        each = told.select(F.explode(f"x{i}").alias("c"), "told").select(F.lit(i).alias("kind"), "c.value", "c.left", "c.right", F.expr(f"CASE WHEN {kin} THEN 1 WHEN {other} THEN 0 END").alias("good"))
        out = each if out is None else out.unionByName(each)
    return out.where("good IS NOT NULL")


def fitted_model(rows: DataFrame) -> tuple:
    """(boosted trees, threshold for each added kind) from a bounded sample of the rows' texts (column text) and made examples; the same for the same rows."""
    spark = rows.sparkSession
    sample = materialise(sampled_rows(rows.select("text"), SAMPLE_DOCS), "pii-sample")
    made = inline_rows(spark, made_candidates(contexts_of(sample, 500)), "kind:int,value:string,left:string,right:string,good:int")
    real = found_candidates(sample)
    real = real.withColumn("h", F.xxhash64("value", "left")).orderBy("h", "value", "left", "right").limit(SAMPLE_FOUND).drop("h")
    features = F.expr(_features("kind", "named_struct('value', value, 'left', left, 'right', right)"))
    got = sorted((list(r["f"]), r["good"], r["value"]) for r in made.unionByName(real).select("good", "value", features.alias("f")).collect())
    random.Random(1).shuffle(got)
    x, y = np.array([g[0] for g in got], float), np.array([g[1] for g in got])
    train = np.arange(len(x)) % 2 == 0
    fitted = trees.fit_boosted(x[train], y[train], rounds=16, depth=4)
    score = 1 / (1 + np.exp(-(fitted[0] + sum(trees.predict(t, x[~train]) for t in fitted[1]))))
    of_kind = [x[~train][:, 0] == k for k in range(len(EXTRA))]
    limits = tuple(max(0.5, trees.calibrated_threshold(score[k], y[~train][k], 0.99)) if k.any() else 1.1 for k in of_kind)
    drop_tables(sample)
    return fitted, limits


def pii_spans(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", extra: bool = True, model: tuple | None = None) -> DataFrame:
    """doc_id, text, email, ip, card, phone (arrays of start, end) and added (array of kind, start, end, score), one row for each row.

    Null and empty texts have no spans, an empty table gives no rows, rows that repeat are read each, a null id is passed on, and other columns are not read. Texts of any length are read whole. Base spans are the leftmost non-overlapping matches of a kind that pass its check; a match that fails is not retried.
    Added spans overlap neither a base span nor one another.
    """
    rows = docs.select(F.col(id_col).alias("doc_id"), text_or_empty(text_col).alias("text")).withColumn("digits", F.col("text").rlike("[0-9]"))
    for kind in BASE_KINDS:
        found = matches("text", PATTERNS[kind])
        worth = f"contains(text, '{HINTS[kind]}')" + ("" if kind == "email" else " AND digits")
        rows = rows.withColumn(kind, F.when(F.expr(worth), found).otherwise(F.expr("cast(array() AS array<struct<start:int,end:int,value:string,left:string,right:string>>)")))
        rows = rows.withColumn(kind, F.expr(f"transform(filter({kind}, c -> {CHECKS[kind]}), c -> named_struct('start', c.start, 'end', c.end))"))
    none = "cast(array() AS array<struct<kind:string,start:int,end:int,score:double>>)"
    if not extra:
        return rows.drop("digits").withColumn("added", F.expr(none))
    model, limits = model or fitted_model(rows)
    rows = rows.withColumn("base", F.expr("concat(email, ip, card, phone)"))
    parts = []
    for k, (kind, pattern) in enumerate(EXTRA.items()):
        hint = f"text RLIKE {quoted(EXTRA_HINTS[kind])}"
        rows = rows.withColumn(f"x{k}", F.when(F.expr(hint), matches("text", pattern)).otherwise(F.expr("cast(array() AS array<struct<start:int,end:int,value:string,left:string,right:string>>)")))
        score = f"1 / (1 + exp(-({model[0]!r}D + {' + '.join(trees._case(t, [f'f.{n}' for n in FEATURES]) for t in model[1])})))"
        open_ = f"filter(x{k}, c -> NOT exists(base, b -> b.start < c.end AND c.start < b.end))"
        scored = f"transform({open_}, c -> named_struct('kind', '{kind}', 'start', c.start, 'end', c.end, 'score', transform(array({_features(str(k))}), f -> {score})[0]))"
        parts.append(f"filter({scored}, c -> c.score >= {limits[k]!r}D)")
    picked = f"aggregate(array_sort(concat({', '.join(parts)}), (a, b) -> CASE WHEN a.score > b.score THEN -1 WHEN a.score < b.score THEN 1 WHEN a.start < b.start THEN -1 WHEN a.start > b.start THEN 1 ELSE 0 END), {none}, (s, c) -> CASE WHEN exists(s, b -> b.start < c.end AND c.start < b.end) THEN s ELSE array_append(s, c) END)"
    some = " OR ".join(f"size(x{k}) > 0" for k in range(len(EXTRA)))
    return rows.withColumn("added", F.expr(f"CASE WHEN {some} THEN {picked} ELSE {none} END")).select("doc_id", "text", *BASE_KINDS, "added")


def _joined(parts: list[str]) -> Column:
    return F.expr(f"array_join(concat({', '.join(parts)}), ',')")


def pii_digests(docs: DataFrame, **options) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_added, n_spans. The four counts are of base spans; added spans have kinds of their own; n_spans counts all."""
    found = pii_spans(docs, **options).drop("text")
    base = [f"transform({k}, c -> concat('{k}:', c.start, ':', c.end))" for k in BASE_KINDS]
    more = [f"transform(array_sort(transform(filter(added, c -> c.kind = '{k}'), c -> named_struct('start', c.start, 'end', c.end))), c -> concat('{k}:', c.start, ':', c.end))" for k in EXTRA]
    rows = found.withColumn("base_spans", _joined(base))
    spans = F.when(F.size("added") == 0, F.col("base_spans")).otherwise(_joined(base + more))
    return rows.select("doc_id", *(F.size(k).cast("long").alias(f"n_{k}") for k in BASE_KINDS), F.sha2("base_spans", 256).alias("base_sha256"), spans.alias("spans"), F.size("added").cast("long").alias("n_added"),
                       F.expr("cast(" + " + ".join(f"size({k})" for k in (*BASE_KINDS, "added")) + " AS bigint)").alias("n_spans"))


def redact(docs: DataFrame, **options) -> DataFrame:
    """doc_id, text with every selected span replaced by its kind in brackets; of overlapping base spans the first by start, then the longest, is replaced."""
    found = pii_spans(docs, **options)
    every = "concat(" + ", ".join(f"transform({k}, c -> named_struct('start', c.start, 'stop', -c.end, 'kind', '{k}'))" for k in BASE_KINDS) + ", transform(added, c -> named_struct('start', c.start, 'stop', -c.end, 'kind', c.kind)))"
    step = "(s, c) -> CASE WHEN c.start < s.at THEN s ELSE named_struct('at', -c.stop, 'out', concat(s.out, substring(text, s.at + 1, c.start - s.at), '[', c.kind, ']')) END"
    return found.select("doc_id", F.expr(f"aggregate(array_sort({every}), named_struct('at', 0, 'out', ''), {step}, s -> concat(s.out, substring(text, s.at + 1)))").alias("text"))
