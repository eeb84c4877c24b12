"""Personal data by a semi-Markov conditional random field.

Exact patterns give the base spans. Around every place where digits or an at-sign stand close together (an island), the
field chooses the best division into segments: whole spans compete by features of the span as a whole and of the words
beside it, and a dynamic program over segments of bounded length chooses boundaries and types together, around the base
spans, which stay. It recovers what the patterns lose, such as a phone number without its plus sign, an address with a
spelled-out at-sign, or a card number divided by dots.

Labels come from the corpus: the base spans of a bounded sample of its islands, as they are and rewritten into forms that
the patterns miss, beside made-up ones for kinds the sample lacks.
"""

from __future__ import annotations

import hashlib
import math
import random
import re
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from worldfold.llm.common import documents

KINDS = ("email", "ip", "card", "phone")

# The base patterns. Possessive repeats and look-behinds only keep them linear.
DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
LOCAL = re.compile(r"[A-Za-z0-9._%+-]+\Z")
IP = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
CARD = re.compile(r"(?<![0-9])[0-9](?:[ -]?[0-9])++")
PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        total += d if i % 2 == 0 else (2 * d - 9 if d > 4 else 2 * d)
    return total % 10 == 0


def only_digits(s: str) -> str:
    return re.sub("[^0-9]", "", s)


_LOCAL_SET = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")


def emails(text: str) -> Iterator[tuple[int, int]]:
    """Leftmost matches, found from their at-signs: the run of name characters before one is read backwards."""
    done, at = 0, text.find("@")
    while at >= 0:
        s = at
        while s > done and text[s - 1] in _LOCAL_SET:
            s -= 1
        if s < at and (m := DOMAIN.match(text, at + 1)):
            yield s, m.end()
            done = m.end()
        at = text.find("@", max(at + 1, done))


def base_spans(text: str) -> list[tuple[str, int, int]]:
    """Spans of the exact patterns by start, then kind in the order of KINDS; ends are exclusive."""
    out = [("email", s, e) for s, e in emails(text)]
    for m in IP.finditer(text):
        if all(len(p := x.lstrip("0")) <= 3 and int(p or 0) <= 255 for x in m.group().split(".")):
            out.append(("ip", *m.span()))
    for m in CARD.finditer(text):
        d = only_digits(m.group()) if m.end() - m.start() <= 40 else ""
        if 14 <= len(d) <= 19 and luhn(d):
            out.append(("card", *m.span()))
    if "+" in text:
        for m in PHONE.finditer(text):
            if 10 <= sum(c.isdigit() and c.isascii() for c in m.group()) <= 15:
                out.append(("phone", *m.span()))
    return sorted(out, key=lambda x: (x[1], KINDS.index(x[0])))


# ---- islands, tokens and candidate segments

MARK = re.compile(r"[0-9@]+|[\[(](?:at|AT)[\])]")
SPELLED = re.compile(r"\b[Aa][Tt](?= [A-Za-z0-9-]+ [Dd][Oo][Tt] )")
REST = re.compile(r"\S*")
TOKEN = re.compile(r"[0-9]+|[A-Za-z]+|\s|.", re.S)
WORD = re.compile(r"[^\W\d_]{2,}")
#: Longest segment in tokens, and characters of context on either side.
SEGMENT, BESIDE = 16, 32


def shape_of(s: str) -> str:
    """Digits run by run with their number, other characters as they are, letters as a."""
    return re.sub(r"[A-Za-z]+", "a", re.sub(r"[0-9]+", lambda m: f"<{len(m.group())}>", s))


@lru_cache(1 << 14)
def _own(kind: str, s: str) -> tuple[str, ...]:
    """Features of the span itself."""
    if kind == "O":
        return ("O", *(["O:digits"] if s.isdigit() else []), *(["O:long"] if s.isdigit() and len(s) >= 7 else []), *(["O:at"] if s == "@" or s.lower() == "at" else []))
    d = only_digits(s)
    n = len(d)
    f = [kind]
    if kind == "card":
        f += [f"luhn={luhn(d)}", f"size={14 <= n <= 19}", f"even={len({len(x) for x in re.findall('[0-9]+', s)[:-1]}) <= 1}"]
    elif kind == "phone":
        f += [f"size={10 <= n <= 15}", f"plus={s[0] == '+'}", f"one={d == s}", f"last={len(re.findall('[0-9]+', s)[-1])}"]
    elif kind == "ip":
        f += [f"range={all(int(p) < 256 and len(p) < 4 for p in re.findall('[0-9]+', s))}", f"zero={any(len(p) > 1 and p[0] == '0' for p in re.findall('[0-9]+', s))}"]
    else:
        f += [f"at={s.count('@')}", f"end={bool(re.search(r'[A-Za-z]{2,}$', s))}", f"dots={min(3, s.count('.') + len(re.findall('(?i)dot', s)))}"]
    if kind != "email":
        f += [f"shape={shape_of(s)}", f"marks={''.join(sorted(set(re.sub('[0-9]', '', s))))}"]
    return (f[0], *[f"{kind}:{x}" for x in f[1:]])


@lru_cache(1 << 12)
def _before(left: str) -> tuple[str, ...]:
    return tuple(f"before={w}" for w in WORD.findall(left.lower())[-2:])


def features(kind: str, s: str, left: str, right: str) -> list[str]:
    """Features of a whole span and of the text beside it; ``O`` is a single token outside."""
    if kind == "O":
        return list(_own(kind, s))
    f = []
    f.append(f"cut={(left[-1:].isalnum() and s[:1].isalnum()) or (right[:1].isalnum() and s[-1:].isalnum())}")
    f.append(f"go={right[:1] in tuple('.-/:_') and right[1:2].isalnum() or left[-1:] in tuple('.-+/:_@') and left[-2:-1].isalnum()}")
    f.append(f"said={left.rstrip()[-1:] in (':', '=', '#')}")
    return [*_own(kind, s), *[f"{kind}:{x}" for x in (*f, *_before(left))]]


def candidates(tokens: list[str], i: int) -> Iterator[tuple[str, int]]:
    """Types and ends of segments that may begin at token i: bounded in tokens and digits, without line ends."""
    first = tokens[i]
    if first.isspace() or not (first.isalnum() and first.isascii() or first in "+("):
        return
    digits = runs = 0
    at = spelled = dot = letters = False
    for j in range(i + 1, min(len(tokens), i + SEGMENT) + 1):
        last = tokens[j - 1]
        if last.isdigit() and last.isascii():
            digits += len(last)
            runs += 1
        elif last == "@":
            if at:
                return
            at = True
        elif last.isalpha():
            word = last.lower()
            spelled |= word == "at" and j > i + 1
            dot |= (at or spelled) and word == "dot"
            letters = True
        elif last not in " .+-_%()[]/":
            return
        elif last == " " and at:
            return
        dot |= last == "." and (at or spelled)
        if digits > 19 and not letters:
            return
        if last.isalnum() and (at or spelled):
            if dot and last.isalpha() and last.lower() not in ("at", "dot"):
                yield "email", j
        elif last.isdigit() and not letters:
            if 7 <= digits <= 15:
                yield "phone", j
            if 12 <= digits <= 19 and first.isdigit():
                yield "card", j
            if runs == 4 and 4 <= digits <= 12 and first.isdigit() and j - i >= 7:
                yield "ip", j


Weights = dict[str, float]


def _tokens(text: str) -> tuple[list[str], list[int]]:
    tokens, at = TOKEN.findall(text), [0]
    for t in tokens:
        at.append(at[-1] + len(t))
    return tokens, at


def lattice(text: str, left: str = "", right: str = "", fixed: list[tuple[int, int]] | None = None) -> tuple[list[int], list[tuple[str, int, int, list[str]]]]:
    """Where tokens begin, and all segments (type, first token, end, features), by their ends. No segment meets a ``fixed`` range."""
    tokens, at = _tokens(text)
    held = [any(at[k] < e and at[k + 1] > s for s, e in fixed or ()) for k in range(len(tokens))]
    around = left + text + right
    out = []
    for i in range(len(tokens)):
        out.append(("O", i, i + 1, features("O", tokens[i], "", "")))
        if not held[i]:
            for kind, j in candidates(tokens, i):
                if any(held[i:j]):
                    break
                s, e = at[i] + len(left), at[j] + len(left)
                out.append((kind, i, j, features(kind, text[at[i] : at[j]], around[max(0, s - BESIDE) : s], around[e : e + 2])))
    return at, sorted(out, key=lambda x: x[2])


def best(text: str, w: Weights, left: str = "", right: str = "", fixed: list[tuple[int, int]] | None = None) -> list[tuple[str, int, int]]:
    """The best division of an island: its spans in characters."""
    at, segments = lattice(text, left, right, fixed)
    top: list[tuple[float, str, int]] = [(0.0, "", 0), *[(-math.inf, "", 0)] * (len(at) - 1)]
    for kind, i, j, f in segments:
        score = top[i][0] + sum(w.get(x, 0.0) for x in f)
        if score > top[j][0]:
            top[j] = (score, kind, i)
    out, e = [], len(at) - 1
    while e:
        _, kind, i = top[e]
        if kind != "O":
            out.append((kind, at[i], at[e]))
        e = i
    return out[::-1]


def _lse(xs: list[float]) -> float:
    m = max(xs)
    return m + math.log(sum(math.exp(x - m) for x in xs))


class Example:
    """An island with its true spans: segments with numbered features, for training."""

    def __init__(self, text: str, left: str, right: str, truth: set[tuple[str, int, int]], number: dict[str, int]):
        at, segments = lattice(text, left, right)
        self.n = len(at) - 1
        inside = [any(at[k] < e and at[k + 1] > s for _, s, e in truth) for k in range(self.n)]
        self.of = [(i, j) for _, i, j, _ in segments]
        #: Spans that no segment can be: the example teaches nothing.
        self.whole = truth <= {(kind, at[i], at[j]) for kind, i, j, _ in segments}
        self.gold = np.array([not inside[i] if kind == "O" else (kind, at[i], at[j]) in truth for kind, i, j, _ in segments], float)
        self.flat = np.array([number.setdefault(x, len(number)) for *_, f in segments for x in f])
        self.start = np.cumsum([0, *[len(f) for *_, f in segments]])[:-1]
        self.owner = np.repeat(np.arange(len(segments)), np.diff(np.append(self.start, len(self.flat))))

    def gradient(self, w: np.ndarray) -> tuple[float, np.ndarray]:
        """Log-likelihood of the true division, and truth minus expectation for each segment, by sums forward and backward."""
        score = np.add.reduceat(w[self.flat], self.start)
        s = score.tolist()
        into: list[list[float]] = [[] for _ in range(self.n + 1)]
        fore = [0.0] * (self.n + 1)
        done = 0
        for k, (i, j) in enumerate(self.of):
            while done < j - 1:
                done += 1
                fore[done] = _lse(into[done])
            into[j].append(fore[i] + s[k])
        fore[self.n] = _lse(into[self.n])
        tail = [0.0] * (self.n + 1)
        out: list[list[float]] = [[] for _ in range(self.n + 1)]
        left = self.n
        for k in range(len(self.of) - 1, -1, -1):
            i, j = self.of[k]
            while left > j:
                left -= 1
                tail[left] = _lse(out[left])
            out[i].append(s[k] + tail[j])
        p = np.array([math.exp(min(0.0, fore[i] + s[k] + tail[j] - fore[self.n])) for k, (i, j) in enumerate(self.of)])
        return float((score * self.gold).sum() - fore[self.n]), self.gold - p


def _sample(r: random.Random) -> tuple[str, set[tuple[str, int, int]]]:
    """A made island: one to three pieces, each personal data or a look-alike, with its true spans."""

    def number(n: int) -> str:
        return str(r.randint(1, 9)) + "".join(str(r.randint(0, 9)) for _ in range(n - 1))

    def card(ok: bool) -> str:
        d = "4" + number(14)
        d += next(str(c) for c in range(10) if luhn(d + str(c)) == ok)
        sep = r.choice(["", "", " ", "-"])
        return sep.join(d[i : i + 4] for i in range(0, 16, 4))

    def phone() -> str:
        a, b, c = number(3), number(3), number(4)
        return r.choice([f"+{r.randint(1, 99)} ({a}) {b}-{c}", f"+{r.randint(1, 9)} {a} {b} {c}", f"+{r.randint(1, 99)}-{a}-{b}-{c}", f"({a}) {b}-{c}", f"+{r.randint(1, 9)}{a}{b}{c}"])

    def ip() -> str:
        return ".".join(str(r.randint(0, 255)) for _ in range(4))

    def email() -> str:
        return f"{r.choice(['anna', 'li', 'jo.smith', 'x_y'])}.{r.randint(1, 99)}@{r.choice(['mail1.', ''])}example.{r.choice(['com', 'org', 'net'])}"

    false = [lambda: number(r.randint(1, 13)), lambda: f"{r.randint(0, 30)}.{r.randint(0, 30)}", lambda: f"{number(4)}-{r.randint(10, 12)}-{r.randint(10, 28)}", lambda: ".".join(str(r.randint(0, 30)) for _ in range(r.choice([3, 5]))), lambda: f"v{r.randint(0, 9)}.{r.randint(0, 9)}", lambda: card(False), lambda: f"({number(2)})", lambda: f"@{r.choice(['home', 'x2'])}", lambda: "".join(r.choice("0123456789abcdef") for _ in range(40)), lambda: f"{number(3)},{number(3)}", lambda: f"{number(5)} {number(5)}", lambda: ".".join(number(3) for _ in range(4)).replace("1", "9"), lambda: number(r.randint(20, 26))]
    make = {"email": email, "ip": ip, "card": lambda: card(True), "phone": phone}
    text, spans = "", set()
    for k in range(r.choice([1, 1, 2, 3])):
        text += " " if k else ""
        kind = r.choice([*KINDS, "O", "O", "O"])
        s = make[kind]() if kind != "O" else r.choice(false)()
        if kind != "O":
            spans.add((kind, len(text), len(text) + len(s)))
        text += s + (r.choice(["", "", ".", ","]) if kind in ("email", "O") else "")
    return text, spans


def rewritten(kind: str, s: str, r: random.Random) -> str:
    """The same data in a form that the patterns do not know."""
    d = only_digits(s)
    if kind == "email":
        name, host = s.split("@")
        dot = r.choice([".", " dot "])
        return name + r.choice([" at ", "(at)", "[at]", " (at) "]) + (host if dot == "." else host.replace(".", dot)) if dot == "." else f"{name} at {host.replace('.', dot)}"
    if kind == "ip":
        return s.replace(".", r.choice(["[.]", "(.)", " . "]))
    if kind == "card":
        return r.choice([".", "_", " - ", "/"]).join(d[i : i + 4] for i in range(0, len(d), 4))
    a, b, c = d[-10:-7], d[-7:-4], d[-4:]
    return r.choice([f"({a}) {b}-{c}", f"{a}-{b}-{c}", f"{a}.{b}.{c}", f"{a} {b} {c}", f"{d[:-10] or 1}-{a}-{b}-{c}", f"00{d[:-10] or 1} {a} {b}{c}"])


Labelled = tuple[str, str, str]  # an island, and what stands before and after it


def _rewrite(text: str, truth: list[tuple[str, int, int]], r: random.Random) -> tuple[str, set[tuple[str, int, int]]]:
    out, spans, at = "", set(), 0
    for kind, s, e in truth:
        if s < at:
            continue
        out += text[at:s]
        new = rewritten(kind, text[s:e], r) if r.random() < 0.7 else text[s:e]
        spans.add((kind, len(out), len(out) + len(new)))
        out, at = out + new, e
    return out + text[at:], spans


def labelled(rows: tuple[Labelled, ...], seed: int = 7) -> list[tuple[str, str, str, set]]:
    """Labels of sampled islands: base spans as they are, and rewritten."""
    r = random.Random(seed)
    out = []
    for text, left, right in rows:
        all_ = base_spans(text)
        truth = [b for i, b in enumerate(all_) if all(b[1] >= e or b[2] <= s for _, s, e in all_[:i])]
        out.append((text, left, right, set(truth)))
        if truth:
            new, spans = _rewrite(text, truth, r)
            out.append((new, left, right, spans))
    return out


@lru_cache(4)
def train(rows: tuple[Labelled, ...] = (), made: int = 300, rounds: int = 12, rate: float = 0.4, penalty: float = 0.002, seed: int = 11) -> tuple[tuple[str, float], ...]:
    """Weights by gradient ascent on labelled islands of the corpus (``rows``) and ``made`` ones; both bound the set."""
    r = random.Random(seed)
    number: dict[str, int] = {}
    data = [Example(t, left, right, truth, number) for t, left, right, truth in labelled(rows)]
    for _ in range(made):
        text, spans = _sample(r)
        cue = r.choice(["", "", r.choice(_CUES[next(iter(spans))[0]]) + r.choice([" ", ": "]) if len(spans) == 1 and text[:1] != " " else ""])
        data.append(Example(text, cue, "", spans, number))
        new, spans = _rewrite(text, sorted(spans, key=lambda x: x[1]), r)
        data.append(Example(new, cue, "", spans, number))
    w, speed = np.zeros(len(number)), np.full(len(number), 1e-8)
    for _ in range(rounds):
        r.shuffle(data)
        for x in data:
            if x.n and x.whole:
                g = x.gradient(w)[1][x.owner]
                at, back = np.unique(x.flat, return_inverse=True)
                step = np.bincount(back, g) - penalty * w[at]
                speed[at] += step * step
                w[at] += rate * step / np.sqrt(speed[at])
    return tuple(sorted((k, round(float(w[i]), 6)) for k, i in number.items() if abs(w[i]) > 1e-4))


#: Words that announce a kind, for made-up islands.
_CUES = {"email": ["email", "mail", "contact", "write to"], "ip": ["ip", "host", "server", "address"], "card": ["card", "visa", "card number", "pay"], "phone": ["call", "phone", "tel", "mobile", "fax"]}


def islands(text: str) -> Iterator[tuple[int, str]]:
    """Runs of words with digits or at-signs, joined by up to three marks or words between, if they hold 4 digits or an at-sign.

    A spelled-out at-sign counts with the words around it.
    """
    marks = [m.span() for m in MARK.finditer(text)]
    if " dot " in text.lower():
        extra = []
        for m in SPELLED.finditer(text):
            e = m.end()
            while (k := re.match(r" [A-Za-z0-9-]+(?: [Dd][Oo][Tt](?= ))?", text[e:])) and (k.group().lower().endswith(" dot") or text[:e].lower().endswith(" dot")):
                e += k.end()
            extra.append((max(0, m.start() - 1), e))
        marks = sorted(marks + extra)
    begin = end = -1
    for s, e in marks:
        if s < end and e <= end:
            continue
        s = min(s, end) if 0 <= end > s else s
        if text[s] in "([" and text[s - 1 : s] == " ":  # "name (at) host"
            s -= 1
        while s > max(0, end) and (not text[s - 1].isspace() or (s >= 1 and text[s : s + 1].isspace())):
            s -= 1
        to = REST.match(text, e).end()
        if text[to - 4 : to].lower() in ("(at)", "[at]") and text[to : to + 1] == " ":
            to = REST.match(text, to + 1).end()
        if begin >= 0 and s <= end + 3 and re.fullmatch(r" ?[-.]? ?", text[end:s] if s > end else ""):
            s = begin
        elif begin >= 0 and _worth(text, begin, end):
            yield begin, text[begin:end]
        begin, end = s, max(end, to)
    if begin >= 0 and _worth(text, begin, end):
        yield begin, text[begin:end]


def _worth(text: str, begin: int, end: int) -> bool:
    s = text[begin:end]
    return "@" in s or SPELLED.search(text, begin, end) is not None or "at)" in s.lower() or "at]" in s.lower() or sum(map(str.isdigit, s)) >= 4


def found(text: str, w: Weights) -> tuple[list, list]:
    """Base spans, and all spans: base ones and those of the field, which divides what is around them."""
    base = base_spans(text)
    added = []
    for at, s in islands(text):
        inside = [b for b in base if b[1] < at + len(s) and b[2] > at]
        left = s
        for _, b, e in inside:
            left = left[: max(0, b - at)] + " " * (min(e - at, len(s)) - max(0, b - at)) + left[e - at :] if e - at < len(s) else left[: max(0, b - at)]
        if not _worth(left, 0, len(left)):
            continue  # no segment can be made of what the patterns leave
        for lo in range(0, len(s), 2000):  # a field over a very long island goes by windows that overlap
            a = at + max(0, lo - 100)
            piece = text[a : at + min(len(s), lo + 2000)]
            fixed = [(b - a, e - a) for _, b, e in inside]
            for kind, b, e in best(piece, w, text[max(0, a - BESIDE) : a], text[a + len(piece) : a + len(piece) + 2], fixed):
                if all(e + a <= x or b + a >= y for _, x, y in added):
                    added.append((kind, b + a, e + a))
    return base, sorted([*base, *added], key=lambda x: (x[1], KINDS.index(x[0])))


#: Islands of the corpus that the field is trained on, and the longest of them.
ISLANDS, LONGEST = 300, 200


def sample_islands(docs: DataFrame, text: str = "text", n: int = ISLANDS) -> tuple[Labelled, ...]:
    """The ``n`` islands with the smallest hashes (with base spans and without, half each) and what stands beside them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for t in b.column(0):
                t = t.as_py()
                for at, s in islands(t):
                    if len(s) <= LONGEST:
                        rows.append((s, t[max(0, at - BESIDE) : at], t[at + len(s) : at + len(s) + 2], bool(base_spans(s))))
            cols = list(zip(*rows, strict=True)) or [()] * 4
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, (pa.string(), pa.string(), pa.string(), pa.bool_()), strict=True)], ["s", "l", "r", "some"])

    rows = docs.select(F.col(text).alias("t")).where(F.col("t").isNotNull()).mapInArrow(run, "s string, l string, r string, some boolean")
    rows = rows.withColumn("h", F.xxhash64("s", "l", "r"))
    top = rows.where("some").orderBy("h", "s", "l", "r").limit(n // 2).unionAll(rows.where("not some").orderBy("h", "s", "l", "r").limit(n // 2))
    return tuple((x["s"], x["l"], x["r"]) for x in top.select("s", "l", "r").collect())


def joined(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{s}:{e}" for k, s, e in spans)


def detect(docs: DataFrame, key: str = "doc_id", text: str = "text", weights: tuple | None = None) -> DataFrame:
    """A row a document: key, n_<kind> (base spans of each kind), base_sha256, spans (all), n_added.

    Offsets are code points. Null or empty text has no spans. Repeated rows are rows of their own. Other columns are
    ignored. Keys are cast to long. The weights (some thousand numbers) are trained on the driver unless given, from ISLANDS
    islands of ``docs``.
    """
    w = dict(weights or train(sample_islands(docs, text)))
    schema = f"{key} long, {', '.join(f'n_{k} long' for k in KINDS)}, base_sha256 string, spans string, n_added long"
    names = [c.split()[0] for c in schema.split(", ")]
    kinds = [pa.int64()] * 5 + [pa.string(), pa.string(), pa.int64()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for k, t in zip(b.column(0), b.column(1), strict=True):
                base, spans = found(t.as_py() or "", w)
                n = Counter(x[0] for x in base)
                rows.append((k.as_py(), *[n[x] for x in KINDS], hashlib.sha256(joined(base).encode()).hexdigest(), joined(spans), len(spans) - len(base)))
            cols = list(zip(*rows, strict=True)) or [()] * len(names)
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], names)

    return docs.select(F.col(key).cast("long").alias(key), F.col(text).alias("text")).mapInArrow(run, schema)


def redact(text: str, spans: list[tuple[str, int, int]]) -> str:
    """Text with each span replaced by its kind in brackets; of spans that overlap the first stays."""
    out, at = [], 0
    for kind, s, e in spans:
        if s >= at:
            out += [text[at:s], f"[{kind}]"]
            at = e
    return "".join(out) + text[at:]


def op4_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return detect(documents(spark, sf_dir))
