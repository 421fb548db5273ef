"""Plain versions of the text contracts, one text at a time."""

import hashlib
import math
import re
from collections import Counter, defaultdict

import regex
import zstandard

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def sha(text):
    return hashlib.sha256(text.encode()).hexdigest()


def normalised(text):
    return re.sub(r"[\x20\x09-\x0D]", "", text or "")


def exact(rows):
    groups = defaultdict(list)
    for i, t in rows:
        groups[normalised(t)].append((-len(t or ""), i is None, i if i is not None else 0, i))
    best = {n: min(g, key=lambda x: x[:3])[3] for n, g in groups.items()}
    return sorted(((i, best[normalised(t)], len(groups[normalised(t)]), i == best[normalised(t)], sha(normalised(t))) for i, t in rows), key=repr)


def lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


def shingles(text, n):
    w = WORD.findall(lower(text))
    return frozenset(tuple(w[k : k + n]) for k in range(len(w) - n + 1)) if len(w) >= n else (frozenset([tuple(w)]) if w else frozenset())


def components(rows, n, percent=80):
    sets = {i: shingles(t, n) for i, t in rows if i is not None}
    parent = {i: i for i in sets}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(i for i in sets if sets[i])
    for k, a in enumerate(ids):
        for b in ids[k + 1 :]:
            both = len(sets[a] & sets[b])
            if both and 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
                x, y = root(a), root(b)
                parent[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), root(i)) for i in sets}


def luhn(s):
    d = [int(c) for c in s if c.isdigit()]
    return 16 <= len(d) <= 19 and sum(x if i % 2 == 0 else (2 * x - 9 if x > 4 else 2 * x) for i, x in enumerate(reversed(d))) % 10 == 0


KINDS = [
    ("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda s: True), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda s: all(int(p) <= 255 for p in s.split("."))),
    ("card", r"[0-9]([\x20-]?[0-9])+", luhn), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]", lambda s: 8 <= sum(c.isdigit() for c in s) <= 15),
]


def pii(text):
    return [[f"{k}:{m.start()}:{m.end()}" for m in re.finditer(p, text or "") if ok(m[0])] for k, p, ok in KINDS]


def quality(text):
    w = WORD.findall(text or "")
    lines = [x for x in (text or "").split("\n") if WORD.search(x)]
    grams = Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
    hit = {i + k for i in range(len(w) - 2) if grams[tuple(w[i : i + 3])] > 1 for k in range(3)}
    n, r = len(w), len(hit)
    return n, sum(map(len, w)), sum(c in "#*$%&|<>" for c in text or ""), len(lines) - len(set(lines)), r, n < 50 or 100 * r > 50 * n


def url(u):
    rest = u.split("://", 1)[1] if u and "://" in u else None
    if rest is None:
        return "", ""
    host = re.match(r"[^/?#]*", rest)[0]
    return lower(host), re.match(r"[^?#]*", rest[len(host) :])[0]


def judge(u, rules, default="allow"):
    host, path = url(u)
    fits = [(len(h + p), len(h), v == "allow", h + p, v) for v, h, p in rules if host and (host == h or host.endswith("." + h)) and path.startswith(p)]
    return (host, path, *(max(fits)[3:] if fits else (None, default)))


def fill(children, budget):
    """Water filling: children name -> (weight, capacity); fractional shares."""
    left, open_, out = budget, dict(children), {}
    while open_:
        total = sum(w for w, _ in open_.values())
        full = {n: c for n, (w, c) in open_.items() if w > 0 and c <= left * w / total + 1e-9}
        if not full:
            out |= {n: left * w / total if total else 0 for n, (w, _) in open_.items()}
            break
        n = min(full, key=lambda x: full[x] / open_[x][0])
        out[n] = full[n]
        left -= full[n]
        del open_[n]
    return out


def isclose(a, b, slack):
    return math.fabs(a - b) <= slack


def spans_with_context(pattern, text, size=32):
    """(start, end, value, left, right) of the matches, contexts up to the neighbouring match."""
    found = list(regex.finditer(pattern, text))
    ends = [0, *(m.end() for m in found)]
    starts = [*(m.start() for m in found), len(text)]
    return [(m.start(), m.end(), m[0], text[ends[i] : m.start()][-size:], text[m.end() : starts[i + 1]][:size]) for i, m in enumerate(found)]


def vote(tree, features):
    while isinstance(tree, tuple):
        at, limit, low, high = tree
        tree = low if features[at] <= limit else high
    return tree


def count(pattern, text):
    return len(regex.findall(pattern, text))


def test(pattern, text):
    return float(bool(regex.search(pattern, text)))


def secret_spans(module, text, path, model):
    """start:end of the candidates that a forest lets pass, one feature after the other."""
    forest, limit, _, known = model
    known, out = set(known), []
    for start, end, value, left, right in spans_with_context(module.PATTERN, text):
        v = regex.sub(module._HEAD, "", value)
        groups = [v[:200][i : i + module.GROUP].lower() for i in range(max(1, len(v[:200]) - module.GROUP + 1))]
        f = [min(len(v), 400), count("[0-9]", v) / len(v), count("[A-Z]", v) / len(v), count("[a-z]", v) / len(v), count("[^A-Za-z0-9]", v) / len(v), count("(?<=[a-z])(?=[A-Z0-9])|(?<=[A-Z])(?=[0-9])|(?<=[0-9])(?=[A-Za-z])", v) / len(v),
             len(set(v[:64])) / min(len(v), 64), sum(g in known for g in groups) / len(groups), count("(?i)(" + "|".join(module.FAKE) + ")", v), test("^[0-9a-f]+$", v), test("^[0-9]+$", v), test(module._HEAD, value),
             test("^(AKIA|ASIA|ghp_|gho_|glpat|sk_live|sk-|xox[bp]|AIza|eyJ)", v), test("(?i)(test|example|sample|fixture|doc)", path), test("(?i)" + module._WORD, left + value),
             test("(?i)(sha-?[0-9]|md5|commit|checksum|uuid|digest|hash|revision|etag|://|href)", left + " " + right[:12]), test(r"(?i)(example|dummy|fake|placeholder|your[_-]|changeme|xxxx|redacted|<)", left + value + right), test(r"(.)\1{4}", v)]
        if sum(vote(t, f) for t in forest) / len(forest) >= limit:
            out.append(f"{start}:{end}")
    return ",".join(out)


def added_spans(module, text, model):
    """kind:start:end of the spans that the boosted trees add to the base ones."""
    (first, boosted), limits = model
    base = [tuple(map(int, x.split(":")[1:])) for kind in pii(text) for x in kind]
    proposed = []
    for number, (kind, pattern) in enumerate(module.EXTRA.items()):
        for start, end, value, left, right in spans_with_context(pattern, text):
            if any(a < end and start < b for a, b in base):
                continue
            f = [number, len(value), count("[0-9]", value), count("[ .-]", value), count("[A-Z]", value), count("(?<=[A-Za-z])(?=[0-9])|(?<=[0-9])(?=[A-Za-z])", value), len(set(value[:64])), test(r"[(\[]", value),
                 test("(?i)^[A-Za-z_-]*" + module._SECRET, value), test("[+][0-9]{1,3}[ .-]?$", left), *(test(cue, left) for cue in module._CUES.values()), test("[0-9A-Za-z]$", left), test("^[0-9A-Za-z%]", right)]
            score = 1 / (1 + math.exp(-(first + sum(vote(t, f) for t in boosted))))
            if score >= limits[number]:
                proposed.append((-score, start, number, end, kind))
    taken = []
    for _, start, number, end, kind in sorted(proposed):
        if not any(a < end and start < b for a, b, *_ in taken):
            taken.append((start, end, number, kind))
    return [f"{kind}:{a}:{b}" for a, b, _, kind in sorted(taken, key=lambda x: (x[2], x[0], x[1]))]


def language(text, dictionaries, level=10, piece=8192):
    """The language whose dictionary makes the folded text smallest, and four times the margin."""
    folded = re.sub(r"[\W\d_]+", " ", (text or "").lower()).strip()
    if not folded:
        return "und", 0.0
    sizes = []
    for order, (lang, content) in enumerate(dictionaries.items()):
        z = zstandard.ZstdCompressor(level=level, dict_data=zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT), write_content_size=False, write_checksum=False, write_dict_id=False)
        sizes.append((sum(len(z.compress(folded[i : i + piece].encode("utf-8", "replace"))) for i in range(0, len(folded), piece)), order, lang))
    sizes.sort()
    return sizes[0][2], min(1.0, 4.0 * (sizes[1][0] - sizes[0][0]) / sizes[1][0]) if len(sizes) > 1 else 1.0


def mixture(rows, order, budgets, max_epochs):
    """{(id, epoch): taken tokens} of leaves' token prefixes: rows (id, leaf, text), order(epoch, id) -> hash, budgets leaf -> tokens."""
    leaves, out = defaultdict(list), {}
    for i, leaf, text in rows:
        n = len(WORD.findall(text or ""))
        if n:
            leaves[leaf].append((i, n))
    for leaf, docs in leaves.items():
        left = budgets[leaf]
        for epoch in range(max_epochs):
            whole = sum(n for _, n in docs)
            for i, n in sorted(docs, key=lambda x: (order(epoch, x[0]), x[0])) if left < whole else docs:
                take = min(n, left)
                if take > 0:
                    out[i, epoch] = take
                    left -= take
    return out


def budgets_of(capacities, weights, total):
    """Integer budgets of leaves (domain, lang, source) by filling level after level with largest remainders."""
    def level(nodes, budget, depth):
        capacity = defaultdict(int)
        for leaf, c in nodes.items():
            capacity[leaf[depth]] += c
        shares = fill({n: (weights(depth, n), c) for n, c in capacity.items()}, min(budget, sum(capacity.values())))
        whole = {n: int(x + 1e-9) for n, x in shares.items()}
        spare = min(budget, sum(capacity.values())) - sum(whole.values())
        for n in sorted(shares, key=lambda n: (shares[n] >= capacity[n] - 1e-9, -(shares[n] - whole[n]), n))[:spare]:
            whole[n] += 1
        out = {}
        for n, share in whole.items():
            below = {leaf: c for leaf, c in nodes.items() if leaf[depth] == n}
            out |= {leaf: share for leaf in below} if depth == 2 else level(below, share, depth + 1)
        return out

    return level(capacities, total, 0)
