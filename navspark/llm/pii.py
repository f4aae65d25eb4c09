"""Personal data: fixed patterns plus a linear-chain conditional random field.

The base kinds (email, ip, card, phone) are found by their patterns in whole texts, in time
linear in the text. The random field adds what patterns miss: secrets, spelled-out addresses,
numbers in other layouts. Its tokens are runs of non-space characters; its features are word
shapes (which character classes occur, length, share of digits, a few cue words) of the token
and its neighbours. It is trained from a small labelled table by gradient ascent on the exact
likelihood and decoded by Viterbi in numpy batches.

Decoding leaves out, without changing the result, tokens that no best path can label: where
the outside label's score leads every other by more than any transition could give back, it is
certain, and the chain falls apart there.

Defined results: null text is empty; repeated rows are scanned each; null ids are carried;
an empty table gives an empty result; extra columns are ignored. Added spans never overlap a
base span, which always stays.
"""

from __future__ import annotations

import hashlib
import random
import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

BASE = ("email", "ip", "card", "phone")
LABELS = ("O", *BASE, "secret")
SLICE = 1 << 21  #: characters of a text whose tokens are labelled at a time

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_DOTTED = re.compile(r"[0-9]++(?:\.[0-9]++)++")
_CARD = re.compile(r"[0-9](?:[ -]?[0-9])++")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")


def emails(text: str) -> list[tuple[int, int]]:
    """Works outwards from each @ sign, so long runs of name characters cost nothing extra."""
    out, done, at = [], 0, text.find("@")
    while at >= 0:
        begin = at
        while begin > done and text[begin - 1] in _LOCAL:
            begin -= 1
        m = _DOMAIN.match(text, at) if begin < at else None
        if m:
            out.append((begin, m.end()))
            done = m.end()
        at = text.find("@", max(done, at + 1))
    return out


def ips(text: str) -> list[tuple[int, int]]:
    """Groups of four parts within each maximal dotted run of digits."""
    out = []
    for m in _DOTTED.finditer(text):
        parts, at = m[0].split("."), m.start()
        for i in range(0, len(parts) - 3, 4):
            four = parts[i : i + 4]
            end = at + sum(map(len, four)) + 3
            if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or "0") <= 255 for p in four):
                out.append((at, end))
            at = end + 1
    return out


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        total += d if i % 2 == 0 else 2 * d - 9 * (d > 4)
    return total % 10 == 0


def _digits(s: str) -> str:
    return re.sub("[^0-9]+", "", s)


def cards(text: str) -> list[tuple[int, int]]:
    return [m.span() for m in _CARD.finditer(text) if 13 <= len(d := _digits(m[0])) <= 19 and luhn(d)]


def phones(text: str) -> list[tuple[int, int]]:
    return [m.span() for m in _PHONE.finditer(text) if 9 <= len(_digits(m[0])) <= 15]


_FINDERS = dict(zip(BASE, (emails, ips, cards, phones), strict=True))


def base_spans(text: str) -> list[tuple[str, int, int]]:
    return [(k, s, e) for k in BASE for s, e in _FINDERS[k](text)]


# --- word shapes -------------------------------------------------------------------------

_KINDS = ("abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789", "@", ".", "-", "_", "+", "()", "=:", "\"'`", "/\\", "[]{}<>", ",;!?", "#$%&*|~^")
_N_KINDS = len(_KINDS) + 1  # and other letters
_LENGTHS = np.array([2, 4, 8, 12, 16, 24, 40])
_DIGIT_SHARES = np.array([0.05, 0.3, 0.6, 0.95])
CUES = ("token", "secret", "password", "passwd", "key", "apikey", "api_key", "bearer", "mail", "email", "at", "dot", "phone", "tel", "call", "card", "ip", "host")


def _kind_table() -> np.ndarray:
    t = np.full(1 << 8, _N_KINDS - 1, np.int64)
    for i, chars in enumerate(_KINDS):
        t[[ord(c) for c in chars]] = i
    t[[ord(c) for c in " \t\n\x0b\x0c\r"]] = -1
    return t


_KIND = _kind_table()
_WEIGHT = np.random.default_rng(0).integers(1, 1 << 61, 64, dtype=np.int64) | 1
_BELOW = np.array([c + 32 if 65 <= c <= 90 else c for c in range(256)], np.int64)


def _cue_hash(codes: np.ndarray, begins: np.ndarray) -> np.ndarray:
    """Hash of each token's lower-cased letters, by their place in the token."""
    low = _BELOW[np.minimum(codes, 255)]
    place = np.arange(len(codes)) - np.repeat(begins, np.diff(np.append(begins, len(codes))))
    return np.add.reduceat(low * _WEIGHT[np.minimum(place, 63)], begins)


def _cue_hashes() -> np.ndarray:
    with np.errstate(over="ignore"):
        return np.array([_cue_hash(np.frombuffer(c.encode("utf-32-le"), np.uint32).astype(np.int64), np.array([0]))[0] for c in CUES])


def tokens_and_shapes(text: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Begin and end of each token and a number that stands for its shape."""
    codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
    kind = _KIND[np.minimum(codes, 255)]
    solid = kind >= 0
    edge = np.diff(np.concatenate([[False], solid, [False]]).astype(np.int8))
    begin, end = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    if not len(begin):
        return begin, end, begin
    kind, codes = kind[solid], codes[solid]
    first = np.cumsum(np.append(0, end - begin))[:-1]
    mask = np.bitwise_or.reduceat(1 << kind, first)
    length = np.searchsorted(_LENGTHS, end - begin)
    share = np.searchsorted(_DIGIT_SHARES, np.add.reduceat((kind == 2).astype(np.float64), first) / (end - begin))
    with np.errstate(over="ignore"):
        word = np.where(np.isin(kind, (0, 1, 6)), codes, 0)  # letters and underscores decide a cue
        h = _cue_hash(word, first)
    cues = _cue_hashes()
    order = np.argsort(cues)
    at = np.minimum(np.searchsorted(cues[order], h), len(cues) - 1)
    cue = np.where(cues[order][at] == h, order[at] + 1, 0)
    return begin, end, ((mask * 8 + length) * 8 + share) * 32 + cue


N_FEATURES = _N_KINDS + 8 + 5 + len(CUES) + 1 + 2


def shape_features(shape: np.ndarray) -> np.ndarray:
    """Indicator rows of shapes; -1 stands for a place outside the text."""
    s = np.maximum(shape, 0)
    cue, s = s % 32, s // 32
    share, s = s % 8, s // 8
    length, mask = s % 8, s // 8
    x = np.zeros((len(shape), N_FEATURES))
    x[:, :_N_KINDS] = mask[:, None] >> np.arange(_N_KINDS) & 1
    rows = np.arange(len(shape))
    x[rows, _N_KINDS + length] = 1
    x[rows, _N_KINDS + 8 + share] = 1
    x[rows, _N_KINDS + 13 + cue] = 1
    x[:, -2] = ((mask & 7) == 5) | ((mask & 7) == 7)  # letters and digits in one token
    x[shape < 0] = 0
    x[:, -1] = shape < 0
    return x


# --- the random field --------------------------------------------------------------------


@dataclass
class Field:
    """Weights of (previous, own, next) token features, label transitions and ends."""

    emit: np.ndarray  # 3, features, labels
    move: np.ndarray  # labels, labels
    begin: np.ndarray
    stop: np.ndarray

    def scores(self, shapes: np.ndarray) -> np.ndarray:
        kinds, at = np.unique(np.concatenate([[-1], shapes]), return_inverse=True)
        by = [shape_features(kinds) @ self.emit[i] for i in range(3)]
        pad = np.concatenate([at[:1], at[1:], at[:1]])
        return by[0][pad[:-2]] + by[1][pad[1:-1]] + by[2][pad[2:]]

    def certain(self, scores: np.ndarray) -> np.ndarray:
        """Tokens that are outside on every best path."""
        into = np.vstack([self.move, self.begin[None]])
        outof = np.hstack([self.move, self.stop[:, None]])
        gain = (into - into[:, :1]).max(0) + (outof - outof[:1]).max(1)
        return (scores[:, :1] > scores[:, 1:] + gain[1:]).all(1)

    def decode(self, scores: np.ndarray, prune: bool = True) -> np.ndarray:
        """Labels of the best path; the stretches between certain tokens are decoded together."""
        n, labels = len(scores), np.zeros(len(scores), np.int64)
        free = ~self.certain(scores) if prune else np.ones(n, bool)
        edge = np.diff(np.concatenate([[False], free, [False]]).astype(np.int8))
        first, last = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
        by_length = np.argsort(first - last, kind="stable")  # longest first
        first, last = first[by_length], last[by_length]
        for a in range(0, len(first), 4096):
            f, e = first[a : a + 4096], last[a : a + 4096]
            size = e - f
            best = scores[f] + np.where((f == 0)[:, None], self.begin, self.move[0])
            back = np.zeros((size.max(), len(f), len(LABELS)), np.int8)
            for t in range(1, size.max()):
                k = int(np.searchsorted(-size, -t, "left"))  # stretches longer than t
                step = best[:k, :, None] + self.move[None]
                back[t, :k] = step.argmax(1)
                best[:k] = step.max(1) + scores[f[:k] + t]
            best = best + np.where((e == n)[:, None], self.stop, self.move[:, 0])
            now = best.argmax(1)
            for t in range(size.max() - 1, -1, -1):
                k = int(np.searchsorted(-size, -t, "left"))
                labels[f[:k] + t] = now[:k]
                if t:
                    now[:k] = back[t, np.arange(k), now[:k]]
        return labels


def train(sequences: list[tuple[np.ndarray, np.ndarray]], rounds: int = 150, rate: float = 0.15, decay: float = 2e-3) -> Field:
    """Maximum likelihood by full-batch Adam; forward and backward sums over padded batches."""
    n, width = len(sequences), max(len(s) for s, _ in sequences)
    y_count = len(LABELS)
    x, y, real = np.zeros((n, width, 3 * N_FEATURES)), np.zeros((n, width), int), np.zeros((n, width), bool)
    for i, (shapes, labels) in enumerate(sequences):
        pad = shape_features(np.concatenate([[-1], shapes, [-1]]))
        x[i, : len(shapes)] = np.hstack([pad[:-2], pad[1:-1], pad[2:]])
        y[i, : len(shapes)], real[i, : len(shapes)] = labels, True
    last = real.sum(1) - 1
    rows = np.arange(n)
    hot = np.eye(y_count)[y] * real[..., None]
    pair = (hot[:, :-1, :, None] * hot[:, 1:, None, :]).sum((0, 1))
    p = {"emit": np.zeros((3 * N_FEATURES, y_count)), "move": np.zeros((y_count, y_count)), "begin": np.zeros(y_count), "stop": np.zeros(y_count)}
    m, v = {k: 0 * a for k, a in p.items()}, {k: 0 * a for k, a in p.items()}

    def total(a, axis):
        top = a.max(axis, keepdims=True)
        return np.squeeze(top, axis) + np.log(np.exp(a - top).sum(axis))

    flat = x.reshape(-1, 3 * N_FEATURES)
    for r in range(1, rounds + 1):
        s = (flat @ p["emit"]).reshape(n, width, y_count)
        fwd, bwd = np.zeros_like(s), np.zeros_like(s)
        fwd[:, 0] = s[:, 0] + p["begin"]
        for t in range(1, width):
            fwd[:, t] = np.where(real[:, t, None], total(fwd[:, t - 1, :, None] + p["move"], 1) + s[:, t], fwd[:, t - 1])
        z = total(fwd[:, -1] + p["stop"], 1)
        bwd[:, -1] = p["stop"]
        for t in range(width - 2, -1, -1):
            on = total(p["move"][None] + (s[:, t + 1] + bwd[:, t + 1])[:, None, :], 2)
            bwd[:, t] = np.where(real[:, t + 1, None], on, p["stop"])
        mean = np.exp(fwd + bwd - z[:, None, None]) * real[..., None]
        joint = np.exp(fwd[:, :-1, :, None] + p["move"] + (s[:, 1:] + bwd[:, 1:])[:, :, None, :] - z[:, None, None, None]) * real[:, 1:, None, None]
        grad = {"emit": flat.T @ (mean - hot).reshape(-1, y_count), "move": joint.sum((0, 1)) - pair, "begin": (mean[:, 0] - hot[:, 0]).sum(0), "stop": (mean[rows, last] - hot[rows, last]).sum(0)}
        for k in p:
            g = grad[k] / n + decay * p[k]
            m[k], v[k] = 0.9 * m[k] + 0.1 * g, 0.99 * v[k] + 0.01 * g * g
            p[k] = p[k] - rate * (m[k] / (1 - 0.9**r)) / (np.sqrt(v[k] / (1 - 0.99**r)) + 1e-8)
    return Field(p["emit"].reshape(3, N_FEATURES, y_count), p["move"], p["begin"], p["stop"])


# --- the labelled table ------------------------------------------------------------------


def labelled_rows(n: int = 600, seed: int = 11) -> list[tuple[str, list[tuple[str, int, int]]]]:
    """A small table of invented sentences with labelled spans, from templates."""
    rnd = random.Random(seed)
    syllables = ["an", "er", "tion", "le", "qu", "sch", "ung", "é", "ció", "ha", "th", "ou", "ñe", "au", "be"]

    def word():
        w = "".join(rnd.choice(syllables) for _ in range(rnd.randint(1, 5)))
        style = rnd.random()
        w = w.capitalize() if style < 0.2 else w.upper() if style < 0.28 else w
        tail = rnd.random()
        return w + (rnd.choice([".", ",", "!!", "***", "###", "$$$", "&&&", "%%%"]) if tail < 0.35 else "")

    def num(k):
        return "".join(rnd.choice("0123456789") for _ in range(k))

    def email():
        user, host = word().strip(".,!*#$&%").lower() + rnd.choice(["", ".", "_"]) + num(rnd.randint(0, 2)), f"mail{num(1)}.example.{rnd.choice(['com', 'org', 'de'])}"
        return rnd.choice([f"{user}@{host}"] * 5 + [f"{user} [at] {host}", f"{user}(at){host}"])

    def ip():
        return ".".join(str(rnd.randint(0, 255)) for _ in range(4))

    def card():
        d = num(rnd.choice([12, 14, 15, 15, 15, 18]))
        d += next(c for c in "0123456789" if luhn(d + c))
        return rnd.choice([d, d, d, " ".join(d[i : i + 4] for i in range(0, len(d), 4)), "-".join(d[i : i + 4] for i in range(0, len(d), 4))])

    def phone():
        return rnd.choice([f"+{num(1)} ({num(3)}) {num(3)}-{num(4)}"] * 3 + [f"+{num(2)} {num(3)} {num(6)}", f"({num(3)}) {num(3)}-{num(4)}", f"{num(3)}-{num(3)}-{num(4)}"])

    def secret():
        body = "".join(rnd.choice("0123456789abcdef") for _ in range(rnd.choice([32, 40, 40, 64])))
        other = "".join(rnd.choice("ABCDEFabcdefXYZxyz0123456789_-") for _ in range(rnd.choice([20, 24, 32])))
        return rnd.choice([body, body, other])

    makers = {"email": email, "ip": ip, "card": card, "phone": phone, "secret": secret}
    cue = {"secret": ["token = ", 'token = "', "api_key: ", "secret=", "password = ", "key = '"], "email": ["", "", "mail ", "email: "], "phone": ["", "", "tel ", "phone: "], "card": ["", "", "card "], "ip": ["", "", "host "]}
    close = {"\"": "\"", "'": "'"}
    out = []
    for _ in range(n):
        text, spans = " ".join(word() for _ in range(rnd.randint(0, 5))), []
        for _ in range(rnd.choice([0, 0, 1, 1, 2])):
            kind = rnd.choice([*makers, "year", "year"])
            text += " " if text else ""
            if kind == "year":
                text += rnd.choice([num(4), num(2), num(1) + ".", f"{num(1)}.{num(2)}", f"{num(2)}%", f"1{num(2)},{num(3)}", f"{num(4)}-{num(2)}-{num(2)}"])
            else:
                lead = rnd.choice(cue[kind])
                value = makers[kind]()
                text += lead
                spans.append((kind, len(text), len(text) + len(value)))
                text += value + close.get(lead[-1:], "") + rnd.choice(["", "", ".", ","])
            text += " " + " ".join(word() for _ in range(rnd.randint(1, 4)))
        out.append((text, spans))
    return out


def labelled_table(spark: SparkSession) -> DataFrame:
    rows = [(t, [f"{k}:{a}:{b}" for k, a, b in s]) for t, s in labelled_rows()]
    return spark.createDataFrame(rows, "text string, spans array<string>")


def train_from(table: DataFrame, max_rows: int = 2000) -> Field:
    """Fit on a labelled table (text, spans as kind:start:end) of at most ``max_rows`` rows."""
    data = []
    for r in table.select("text", "spans").limit(max_rows).collect():
        begin, end, shapes = tokens_and_shapes(r.text or "")
        if len(begin):
            y = np.zeros(len(begin), int)
            for s in r.spans or []:
                kind, a, b = s.split(":")
                y[(begin < int(b)) & (end > int(a))] = LABELS.index(kind)
            data.append((shapes, y))
    return train(data)


# --- spans -------------------------------------------------------------------------------

_TRIM = " \t\n\x0b\x0c\r.,;:!?\"'`()[]{}<>*#$%&|=~^"
_LEAD = re.compile(r"(?i)^(?:[a-z_]{2,20}[=:]+)?[\"'`(\[]*")


def _cut(text: str, kind: str, a: int, b: int) -> tuple[int, int]:
    """Leaves out punctuation at both ends and, before a secret, the name it is given to."""
    if kind == "secret":
        a += _LEAD.match(text[a:b]).end()
    keep = "(+" if kind == "phone" else ""
    while a < b and text[a] in _TRIM and text[a] not in keep:
        a += 1
    while a < b and text[b - 1] in _TRIM:
        b -= 1
    return a, b


def _confirmed(text: str, kind: str, a: int, b: int) -> tuple[int, int] | None:
    """The span if its digits bear its kind out: a card number's check digit, an address's parts,
    a phone number's length (a number that runs on gives up its last groups)."""
    while a < b:
        value = text[a:b]
        n = len(d := _digits(value))
        if kind == "card":
            return (a, b) if 13 <= n <= 19 and luhn(d) else None
        if kind == "ip":
            parts = value.split(".")
            return (a, b) if len(parts) == 4 and all(p.isdecimal() and len(p) <= 3 and int(p) <= 255 for p in parts) else None
        if kind != "phone" or 7 <= n <= 15:
            return a, b
        cut = max(value.rfind(" "), value.rfind("\n"), value.rfind("\t"))
        if n < 7 or cut < 0:
            return None
        a, b = _cut(text, kind, a, a + cut)
    return None


def added_spans(text: str, field: Field) -> list[tuple[str, int, int]]:
    out = []
    at = 0
    while at < len(text):
        stop = min(len(text), at + SLICE)
        while stop < len(text) and _KIND[min(ord(text[stop]), 255)] >= 0:
            stop += 1
        begin, end, shapes = tokens_and_shapes(text[at:stop])
        if len(begin):
            labels = field.decode(field.scores(shapes))
            cut = np.flatnonzero(np.diff(np.concatenate([[0], labels, [0]])))
            for i, j in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True):
                if labels[i]:
                    kind = LABELS[labels[i]]
                    span = _confirmed(text, kind, *_cut(text, kind, at + int(begin[i]), at + int(end[j - 1])))
                    if span:
                        out.append((kind, *span))
        at = stop
    return out


def all_spans(text: str, field: Field) -> tuple[list, list]:
    """(base spans, all spans), each by kind in the order of ``LABELS``, then start."""
    base = base_spans(text)
    taken = sorted((a, b) for _, a, b in base)
    starts = [a for a, _ in taken]
    reach = list(np.maximum.accumulate([b for _, b in taken])) if taken else []
    extra = []
    for kind, a, b in added_spans(text, field):
        i = int(np.searchsorted(starts, b)) if starts else 0  # base spans that begin before b
        if not i or reach[i - 1] <= a:
            extra.append((kind, a, b))
    every = sorted(base + extra, key=lambda s: (LABELS.index(s[0]), s[1]))
    return base, every


def personal_data(docs: DataFrame, field: Field) -> DataFrame:
    """doc_id, base and spans (arrays of kind, start, end) of each row."""

    def run(batches):
        span = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))
        for b in batches:
            base, every = [], []
            for t in b.column("text"):
                x, y = all_spans(t.as_py() or "", field)
                base.append([{"kind": k, "start": s, "end": e} for k, s, e in x])
                every.append([{"kind": k, "start": s, "end": e} for k, s, e in y])
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(base, span), pa.array(every, span)], ["doc_id", "base", "spans"])

    kind = "array<struct<kind:string,start:bigint,end:bigint>>"
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, f"doc_id long, base {kind}, spans {kind}")


def op2_result(docs: DataFrame, table: DataFrame | None = None) -> DataFrame:
    field = train_from(table if table is not None else labelled_table(docs.sparkSession))
    got = personal_data(docs, field)

    def joined(c):
        return F.array_join(F.transform(c, lambda s: F.concat_ws(":", s.kind, s.start.cast("string"), s["end"].cast("string"))), ",")

    def count(kind):
        return F.size(F.filter("base", lambda s: s.kind == kind)).cast("long").alias(f"n_{kind}")

    counts = [count(k) for k in BASE]
    return got.select("doc_id", *counts, F.sha2(joined("base"), 256).alias("base_sha256"), joined("spans").alias("spans"))


def sha256_of(spans: list[tuple[str, int, int]]) -> str:
    return hashlib.sha256(",".join(f"{k}:{a}:{b}" for k, a, b in spans).encode()).hexdigest()
