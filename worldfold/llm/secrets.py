"""Secret scans whose false positives a random forest takes out.

Candidates are runs of characters that keys are made of. Each is described by whole numbers: length, how often the
character class changes and from which to which, how much of it dictionary words cover, how it would be spoken, whether it
looks like a path, and the words beside it.
A forest fitted on labelled findings scores them. The fitted trees become one SQL expression, so finding, describing and
scoring stay in the engine; only the few hundred labelled findings are seen by Python, on the driver.
"""

from __future__ import annotations

import random
import re
from functools import lru_cache

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from worldfold.llm.common import documents

# Patterns are valid for Java, RE2 and Python alike and free of backslashes, so one text serves all three.
CANDIDATE = "[A-Za-z0-9_+/-]{16,}"
#: Characters kept on either side.
BESIDE = 40
#: Words that code and prose put into names.
DICTIONARY = "about|access|account|admin|alpha|application|array|article|base|beta|block|build|button|cache|card|category|change|class|client|code|commit|common|component|config|content|control|count|create|data|date|debug|default|demo|device|dummy|example|field|file|filter|format|function|group|handler|hash|header|home|host|image|index|info|input|issue|item|key|label|layout|level|library|list|local|manager|master|menu|message|method|model|module|name|network|node|number|object|option|order|output|package|page|param|path|placeholder|plugin|product|project|public|query|record|release|request|response|result|sample|schema|score|script|search|section|service|session|setting|source|start|state|static|status|string|style|system|table|target|template|test|text|theme|title|type|update|user|value|version|view|widget|window|your"
FIELDS = {
    "named": "(?i)(secret|token|passw(or)?d|pwd|api_?-?key|apikey|access_?-?key|auth|bearer|credential|private_?-?key)[a-z_]*[\"']?[ ]*(=|:|=>|[ ])[ ]*[\"']?$",
    "hashed": "(?i)(commit|sha-?[0-9]*|md5|checksum|digest|etag|revision|rev|uuid|guid|build|version|order|card|isbn|ref|page|img|id)[\"']?[ ]*(=|:|#|[ ])[ ]*[\"']?$",
    "quoted": "[\"'`]$",
    "equals": "[=:][ ]*[\"']?$",
    "linked": "(https?:|www[.]|href|src)[^ ]*$",
}
#: Labelled findings the forest is fitted on, trees, and how deep they go: bounds of the fit.
FINDINGS, TREES, DEPTH, VOTE = 1200, 15, 6, 1000
#: A finding is reported as a secret from this mean vote on.
SURE = 500

#: Changes of class from one character to the next, and runs that words do not have.
TURNS = {"to_letter": "[0-9][A-Za-z]", "to_digit": "[A-Za-z][0-9]", "to_upper": "[a-z][A-Z]", "to_lower": "[A-Z][a-z]", "unspoken": "[bcdfghjklmnpqrstvwxz][bcdfghjklmnpqrstvwxz][bcdfghjklmnpqrstvwxz][bcdfghjklmnpqrstvwxz]", "same": "(aa|bb|cc|dd|ee|ff|xx|00|11|22|33|44|55|66|77|88|99|--|__)"}
FEATURES = ["size", "digits", "uppers", "lowers", "vowels", "runs", *TURNS, "words", "slashes", "marks", "hexed", "keyed", "kinds", *FIELDS, "told", "ended"]
KEYED = "^(AKIA|ASIA|ghp_|gho_|sk_live_|sk-|xoxb-|xoxp-|AIza|glpat-|eyJ)"
ENDED = "^[.](py|js|ts|html?|css|png|jpe?g|gif|svg|json|xml|txt|md|zip|gz|pdf)"


def describe(left: str, c: str, right: str) -> list[int]:
    """The features of a finding in Python; ``columns`` says the same in SQL."""

    def runs(s: str) -> int:
        for pat, one in (("[0-9]+", "0"), ("[a-z]+", "a"), ("[A-Z]+", "A"), ("[^0-9a-zA-Z]+", "_")):
            s = re.sub(pat, one, s)
        return len(s)

    n = len(c)
    share = lambda pat: (n - len(re.sub(pat, "", c))) * 100 // n
    low = c.lower()
    seen = [bool(re.search(p, left)) for p in FIELDS.values()]
    kinds = sum(bool(re.search(p, c)) for p in ("[0-9]", "[a-z]", "[A-Z]", "[^0-9a-zA-Z]"))
    # a match of k characters leaves one: the length shrinks by k - 1 for each
    turns = [(n - len(re.sub(p, "~", low if k in ("unspoken", "same") else c))) * 100 // n for k, p in TURNS.items()]
    told = len(left) - len(re.sub(DICTIONARY, "", left.lower()))
    return [n, share("[0-9]"), share("[A-Z]"), share("[a-z]"), share("[aeiouAEIOU]"), runs(c) * 100 // n, *turns, (n - len(re.sub(DICTIONARY, "", low))) * 100 // n, n - len(re.sub("/", "", c)), n - len(re.sub("[_-]", "", c)), int(bool(re.search("^([0-9a-f]+|[0-9A-F]+)$", c))), int(bool(re.search(KEYED, c))), kinds, *map(int, seen), told, int(bool(re.search(ENDED, right)))]


def columns(duckdb: bool = False) -> dict[str, str]:
    """SQL of each feature over the columns l (left), c (candidate) and r (right)."""
    q = lambda p: "'" + p.replace("'", "''" if duckdb else "\\'") + "'"
    sub = (lambda s, p, x="": f"regexp_replace({s}, {q(p)}, '{x}', 'g')") if duckdb else (lambda s, p, x="": f"regexp_replace({s}, {q(p)}, '{x}')")
    has = (lambda s, p: f"CAST(regexp_matches({s}, {q(p)}) AS BIGINT)") if duckdb else (lambda s, p: f"CAST(regexp_like({s}, {q(p)}) AS BIGINT)")
    part = lambda a, b: f"(({a}) * 100 // ({b}))" if duckdb else f"(({a}) * 100 div ({b}))"
    n = "length(c)"
    share = lambda p: part(f"{n} - length({sub('c', p)})", n)
    runs = "c"
    for pat, one in (("[0-9]+", "0"), ("[a-z]+", "a"), ("[A-Z]+", "A"), ("[^0-9a-zA-Z]+", "_")):
        runs = sub(runs, pat, one)
    out = {"size": n, "digits": share("[0-9]"), "uppers": share("[A-Z]"), "lowers": share("[a-z]"), "vowels": share("[aeiouAEIOU]"), "runs": part(f"length({runs})", n)}
    out |= {k: part(f"{n} - length({sub('lower(c)' if k in ('unspoken', 'same') else 'c', p, '~')})", n) for k, p in TURNS.items()}
    out["words"] = part(f"{n} - length({sub('lower(c)', DICTIONARY)})", n)
    out["slashes"] = f"{n} - length({sub('c', '/')})"
    out["marks"] = f"{n} - length({sub('c', '[_-]')})"
    out["hexed"] = has("c", "^([0-9a-f]+|[0-9A-F]+)$")
    out["keyed"] = has("c", KEYED)
    out["kinds"] = " + ".join(has("c", p) for p in ("[0-9]", "[a-z]", "[A-Z]", "[^0-9a-zA-Z]"))
    out |= {k: has("l", p) for k, p in FIELDS.items()}
    out["told"] = f"length(l) - length({sub('lower(l)', DICTIONARY)})"
    out["ended"] = has("r", ENDED)
    return {k: f"CAST({v} AS BIGINT)" for k, v in out.items()}


def labelled(n: int = FINDINGS, seed: int = 5) -> list[tuple[str, str, str, int]]:
    """Labelled findings (left, candidate, right, is a secret), made by rule: half secrets, half look-alikes."""
    r = random.Random(seed)
    pick = lambda chars, k: "".join(r.choice(chars) for _ in range(k))
    hex_, up, mixed = "0123456789abcdef", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567", "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789"
    syllables = ["th", "er", "on", "an", "re", "he", "in", "ed", "nd", "ha", "at", "en", "es", "of", "or", "nt", "ea", "ti", "to", "it", "st", "io", "le", "is", "ou", "ar", "as", "de", "rt", "ve"]
    word = lambda: pick(syllables, r.randint(2, 5))
    prose = lambda: " ".join(word() for _ in range(5)) + r.choice([" ", ". ", ", "])
    names = DICTIONARY.split("|")

    def secret() -> tuple[str, str, str]:
        body = r.choice([lambda: pick(hex_, r.choice([18, 20, 24, 32, 40, 64])), lambda: pick(mixed, r.choice([20, 24, 32, 40, 43])), lambda: pick(mixed + "+/", 40)])
        name = r.choice(["token", "secret", "password", "passwd", "api_key", "apikey", "access_key", "auth_token", "client_secret", "private_key", "Bearer", "API_KEY", "aws_secret_access_key", "STRIPE_SECRET_API_KEY", "github-access-token-value"])
        return r.choice([
            lambda: (prose() + name + r.choice([" = \"", "=", ": ", ": \"", " = '", "=\""]), body(), r.choice(["\"", " ", "'", ""]) + word()),
            lambda: (prose(), r.choice([lambda: "AKIA" + pick(up, 16), lambda: "ghp_" + pick(mixed, 36), lambda: "sk_live_" + pick(mixed, 24), lambda: "AIza" + pick(mixed, 35), lambda: "glpat-" + pick(mixed, 20), lambda: "eyJ" + pick(mixed, 60)])(), " " + word()),
        ])()

    def other() -> tuple[str, str, str]:
        return r.choice([
            lambda: (prose(), pick("0123456789", r.choice([16, 16, 17, 18, 20])), " " + word()),
            lambda: (prose() + r.choice(["commit ", "sha256:", "md5: ", "rev ", "checksum=", "digest: ", "etag=\"", "uuid="]), pick(hex_, r.choice([32, 40, 64])), " " + word()),
            lambda: (prose() + "uuid ", "-".join(pick(hex_, k) for k in (8, 4, 4, 4, 12)), " "),
            lambda: (prose(), word() + word() + word() + word() + pick(syllables, 4), " " + word()),
            lambda: (prose() + "/", "/".join(r.choice(names) for _ in range(r.randint(3, 5))) + "/" + r.choice(names) + str(r.randint(1, 99)), r.choice([".py", ".html", ".png", ""]) + " "),
            lambda: (prose(), r.choice(names) + "".join(x.title() for x in r.sample(names, 3)) + r.choice(["", str(r.randint(1, 9))]), "() "),
            lambda: (prose(), "_".join(r.sample(names, 4)), " "),
            lambda: (prose() + r.choice(["token = \"", "password=", "api_key: "]), r.choice(["your_api_key_goes_here", "example_token_placeholder", "dummy-password-value-test", "user_password_field_name"]), "\" "),
            lambda: ("http://www.example.com/" + word() + "?" + r.choice(["id=", "page=", "ref="]), pick(hex_, r.choice([16, 20, 24])), " "),
            lambda: (prose(), pick("-", 20) if r.random() < 0.5 else pick("_", 24), " "),
            lambda: (prose(), pick("ABCDEFGHIJKLMNOPQRSTUVWXYZ", r.randint(16, 24)), " "),
        ])()

    out = []
    for i in range(n):
        left, c, right = other() if i % 2 else secret()
        m = re.search(CANDIDATE, c)
        if m:
            out.append((left[-BESIDE:] if m.start() == 0 else c[: m.start()], m.group(), right[:BESIDE], int(i % 2 == 0)))
    return out


def _grow(x: np.ndarray, y: np.ndarray, depth: int, r: np.random.Generator):
    """A tree as nested (feature, limit, not above, above) with whole-number votes as leaves."""
    vote = int(round(y.mean() * VOTE))
    if depth == 0 or vote in (0, VOTE) or len(y) < 8:
        return vote
    best = None
    for f in r.choice(x.shape[1], 5, replace=False):
        values = np.unique(x[:, f])
        for limit in values[:-1] if len(values) <= 12 else np.unique(np.quantile(values[:-1], np.linspace(0, 1, 12)).astype(np.int64)):
            low = x[:, f] <= limit
            k = low.sum()
            if 3 <= k <= len(y) - 3:
                a, b = y[low].mean(), y[~low].mean()
                impure = k * a * (1 - a) + (len(y) - k) * b * (1 - b)
                if best is None or impure < best[0]:
                    best = (impure, int(f), int(limit), low)
    if best is None:
        return vote
    _, f, limit, low = best
    return (f, limit, _grow(x[low], y[low], depth - 1, r), _grow(x[~low], y[~low], depth - 1, r))


@lru_cache(4)
def forest(findings: int = FINDINGS, trees: int = TREES, depth: int = DEPTH, seed: int = 3) -> tuple:
    data = labelled(findings)
    x, y = np.array([describe(*d[:3]) for d in data]), np.array([d[3] for d in data], float)
    r = np.random.default_rng(seed)
    grown = []
    for _ in range(trees):
        bag = r.integers(0, len(y), len(y))
        grown.append(_grow(x[bag], y[bag], depth, r))
    return tuple(grown)


def vote_of(tree, values: list[int]) -> int:
    while not isinstance(tree, int):
        tree = tree[2] if values[tree[0]] <= tree[1] else tree[3]
    return tree


def score(values: list[int], trees: tuple) -> int:
    return sum(vote_of(t, values) for t in trees) // len(trees)


def _case(tree) -> str:
    if isinstance(tree, int):
        return str(tree)
    return f"CASE WHEN {FEATURES[tree[0]]} <= {tree[1]} THEN {_case(tree[2])} ELSE {_case(tree[3])} END"


def score_sql(trees: tuple, duckdb: bool = False) -> str:
    """The forest's mean vote over the feature columns, as one expression."""
    return f"CAST(({' + '.join(map(_case, trees))}) {'//' if duckdb else 'div'} {len(trees)} AS BIGINT)"


def findings(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """A row a candidate: key, ordinal (from 0 in its text), l, c, r. Null and empty texts have none."""
    found = F.regexp_extract_all(text, F.lit(CANDIDATE), F.lit(0))
    rows = docs.where(F.regexp_like(text, F.lit(CANDIDATE))).select(F.col(key).alias("key"), found.alias("found"), F.split(text, CANDIDATE, -1).alias("gaps"))
    rows = rows.select("key", "gaps", "found", F.posexplode("found").alias("ordinal", "c"))
    before = "concat(CASE WHEN ordinal > 0 THEN element_at(found, ordinal) ELSE '' END, element_at(gaps, ordinal + 1))"  # a name may be a candidate itself
    return rows.select("key", F.col("ordinal").cast("long").alias("ordinal"), F.expr(f"right({before}, {BESIDE})").alias("l"), "c", F.expr(f"left(element_at(gaps, ordinal + 2), {BESIDE})").alias("r"))


def scan(docs: DataFrame, key: str = "doc_id", text: str = "text", sure: int = SURE, trees: tuple | None = None) -> DataFrame:
    """A row a candidate: key, ordinal, candidate_md5, size, score (0 to 1000), secret (score at least ``sure``).

    Candidates themselves are not passed on. Whole texts are read, in one pass without a shuffle. Repeated rows give
    repeated findings; an empty table gives none. Other columns are ignored.
    """
    f = findings(docs, key, text)
    f = f.select("key", "ordinal", F.md5(F.col("c").cast("binary")).alias("candidate_md5"), *[F.expr(v).alias(k) for k, v in columns().items()])
    f = f.withColumn("score", F.expr(score_sql(trees or forest())))
    return f.select(F.col("key").alias(key), "ordinal", "candidate_md5", "size", "score", (F.col("score") >= sure).alias("secret"))


def op9_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(documents(spark, sf_dir))


def oracle() -> str:
    feats = ", ".join(f"{v} AS {k}" for k, v in columns(duckdb=True).items())
    return f"""
WITH f AS (
  SELECT doc_id, regexp_extract_all(text, '{CANDIDATE}') AS found, regexp_split_to_array(text, '{CANDIDATE}') AS gaps FROM documents),
e AS (SELECT doc_id, gaps, found, unnest(found) AS c, unnest(range(len(found))) AS ordinal FROM f),
k AS (SELECT doc_id, ordinal, c, right((CASE WHEN ordinal > 0 THEN found[ordinal] ELSE '' END) || gaps[ordinal + 1], {BESIDE}) AS l, left(gaps[ordinal + 2], {BESIDE}) AS r FROM e),
x AS (SELECT doc_id, ordinal, md5(c) AS candidate_md5, {feats} FROM k),
s AS (SELECT doc_id, ordinal, candidate_md5, size, {score_sql(forest(), duckdb=True)} AS score FROM x)
SELECT doc_id, ordinal, candidate_md5, size, score, score >= {SURE} AS secret FROM s
"""
