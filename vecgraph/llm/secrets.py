"""Secret scans: three fixed patterns and a linear-chain conditional random field.

The patterns give the base spans. The field tags tokens as secret begin (B), inside (I) or outside (O) from
the token's shape, the words before and after it and features of the whole text, decoded by Viterbi; its
spans are added where they touch no base span. It is trained here, on generated lines (no corpus rows).

Only cue words and signs say anything about the tokens beside them. Most other tokens' best score for B or I
stays below that for O by more than file features and transitions could add. Such tokens are O in every best
path, so they cut a text into short pieces; only pieces with other tokens, or beside cues, are decoded, and
the result is that of decoding the whole text.

Defined cases: a null text counts as empty; empty texts have no spans; repeated rows stay; spans are code
points, end exclusive, ordered by start, then kind in the order of KINDS.
"""

from __future__ import annotations

import hashlib
import re
import string
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from vecgraph.session import ship

from .common import column, id_text, small, strings

KINDS = ("assign", "access", "hex", "crf")
# fixed values: the three base patterns and their least lengths
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.ASCII | re.IGNORECASE)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]+")
LEAST = {"assign": 6, "access": 20, "hex": 24}

_HEX_MAP = bytes(120 if chr(c) in "0123456789abcdef" else 32 for c in range(256))
_HEX_RUN = b"x" * LEAST["hex"]


def base_spans(text: str, data: bytes | None = None) -> list[tuple[int, str, int]]:
    """(start, kind, end), in order of start and kind. Cheap exact tests skip texts a pattern can't match."""
    out = []
    data = text.encode("utf-8", "surrogatepass") if data is None else data
    low = data.lower()
    if any(w in low for w in (b"passw", b"secret", b"token", b"api")):
        out += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= LEAST["assign"]]
    if b"AKIA" in data:
        out += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if len(m[0]) >= LEAST["access"]]
    if _HEX_RUN in data.translate(_HEX_MAP):
        out += [(m.start(), 2, m.end()) for m in HEX.finditer(text) if len(m[0]) >= LEAST["hex"]]
    return [(s, KINDS[k], e) for s, k, e in sorted(out)]


# ---- the field ----

B, I, O = 0, 1, 2
TOKEN = re.compile(r"[\w+/.=-]+|[^\w\s]")
CUES = ("password", "passwd", "pwd", "passphrase", "secret", "token", "apikey", "api_key", "key", "bearer", "auth", "authorization", "credential", "credentials", "access", "private", "pin")


def _shape(token: str) -> list[str]:
    n = len(token)
    digits = sum(c.isdigit() for c in token)
    upper, lower = sum(c.isupper() for c in token), sum(c.islower() for c in token)
    kinds = (digits > 0) + (upper > 0) + (lower > 0)
    turns = sum((a.isdigit(), a.isupper(), a.islower()) != (b.isdigit(), b.isupper(), b.islower()) for a, b in zip(token, token[1:], strict=False))
    size = 0 if n < 3 else 1 if n < 6 else 2 if n < 10 else 3 if n < 20 else 4
    turning = min(3, 8 * turns // n) if n > 1 else 0
    if n == 1 and not token.isalnum():
        return ["p:" + (token if token in ":=\"'|,;()<>@#*" else "other")]
    out = [f"k:{kinds}:{size}", f"t:{turning}:{size}", f"d:{min(4, 5 * digits // n)}"]
    if digits == n:
        out.append(f"number:{size}")
    if token.isalpha() and (token.islower() or token.istitle()):
        out.append("word")
    if "." in token[1:-1] or "/" in token[1:-1]:
        out.append("dotted")
    if "-" in token or "_" in token:
        out.append("joined")
    return out


def _word(token: str) -> str | None:
    w = token.lower().rstrip("=:")
    if w in CUES:
        return "cue:" + w
    if token in ":=\"'":
        return "sign:" + token
    return None


def own_features(token: str) -> list[str]:
    return [*_shape(token), *(["own:" + w] if (w := _word(token)) else [])]


def side_features(token: str) -> list[str]:
    """What a token tells about the one beside it (and the one after that, where signs stand between)."""
    return [w] if (w := _word(token)) else []


def file_features(text: str) -> list[str]:
    n, low = len(text) + 1, text.lower()
    return ["file:signs" if 60 * (text.count("=") + text.count(":")) > n else "file:plain", "file:cue" if any(c in low for c in ("passw", "secret", "token", "key", "auth")) else "file:nocue"]


def generated(seed: int = 5, lines: int = 1500) -> list[tuple[list[str], list[int], list[str]]]:
    """Training lines: (tokens, tags, file features). Secrets of several alphabets in several settings, and prose,
    numbers, addresses, dates, cards, phones, links and markup that are none."""
    r = np.random.default_rng(seed)
    pick = lambda xs: xs[int(r.integers(len(xs)))]
    chars = lambda abc, lo, hi: "".join(pick(abc) for _ in range(int(r.integers(lo, hi))))
    vowels, others = "aeiou", "bcdfghlmnprstvz"
    word = lambda: "".join(pick(others) + pick(vowels) for _ in range(int(r.integers(1, 5)))) + pick(["", "n", "s", ""])
    cased = lambda: pick([str.lower, str.lower, str.title, str.upper])(word())
    mixed = string.ascii_letters + string.digits
    secret = lambda: pick([lambda: chars(mixed, 10, 44), lambda: chars("0123456789abcdef", 20, 48), lambda: chars(mixed + "+/", 16, 44), lambda: "sk-" + chars(mixed, 16, 40), lambda: chars(string.ascii_lowercase + string.digits, 12, 32), lambda: "ghp_" + chars(mixed, 20, 36)])()
    weak = lambda: word() + chars(string.digits, 2, 5)
    noise = lambda: pick([lambda: chars(string.digits, 1, 17), lambda: ".".join(chars(string.digits, 1, 4) for _ in range(4)), lambda: f"+1 ({chars(string.digits, 3, 4)}) {chars(string.digits, 3, 4)}-{chars(string.digits, 4, 5)}", lambda: f"{word()}.{chars(string.digits, 2, 3)}@mail.example.com", lambda: f"https://{word()}.example.com/{word()}/{chars(string.digits, 2, 5)}", lambda: "2024-0" + chars("123456789", 1, 2) + "-12", lambda: word() + pick(["***", "$$$", "!!", "%%%", "###"]), lambda: word().upper(), lambda: "v1." + chars(string.digits, 1, 3), lambda: word() + "-" + word(), lambda: "<" + word() + ">"])()
    out = []
    for _ in range(lines):
        before = " ".join(pick([cased, cased, cased, noise])() for _ in range(int(r.integers(0, 10))))
        after = " ".join(pick([cased, cased, cased, noise])() for _ in range(int(r.integers(0, 10))))
        kind = r.random()
        hidden, middle = "", ""
        if kind < 0.45:
            hidden = secret()
            cue = pick([*CUES[:-1]])
            middle = pick([f"{cue} {{}}", f"{cue}: {{}}", f'{cue} = "{{}}"', f"{cue} is {{}}", f"Authorization: Bearer {{}}", f"{cue} -> {{}}", "{}"]).format("\x00")
        elif kind < 0.6:
            hidden = weak()
            middle = pick(["password {}", "password is {}", "pwd: {}", "passwd {}", "passphrase = {}"]).format("\x00")
        text = f"{before} {middle} {after}"
        at = text.find("\x00")
        full = text.replace("\x00", hidden)
        tokens, tags, inside = [], [], False
        for m in TOKEN.finditer(full):
            tokens.append(m[0])
            ours = at >= 0 and m.start() < at + len(hidden) and m.end() > at
            tags.append((I if inside else B) if ours else O)
            inside = ours
        if tokens:
            out.append((tokens, tags, file_features(full)))
    return out


class _Forms(dict):
    """Field.form by token, in a table of bounded size; plain lower-case and title-case words share a form by length."""

    def __init__(self, field: Field) -> None:
        super().__init__()
        self.field, self.plain = field, {n: field.form("b" * n) for n in range(1, 21)}
        self.titled = {n: field.form("B" + "b" * (n - 1)) for n in range(1, 21)}

    def __missing__(self, token: str) -> int:
        alpha = token.isalpha() and token.lower() not in CUES
        if alpha and token.islower():
            f = self.plain[min(len(token), 20)]
        elif alpha and token.istitle():
            f = self.titled[min(len(token), 20)]
        else:
            f = self.field.form(token)
        if len(self) >= 400_000:
            self.clear()
        self[token] = f
        return f


class Field:
    """Weights by feature and tag for the token itself, its two neighbours before and one after, and the file; transitions by tag pair."""

    PLACES = ("own", "prev", "prev2", "next", "file")

    def __init__(self) -> None:
        self.index: dict[tuple[str, str], int] = {}
        self.w = np.zeros((0, 3))
        self.trans = np.zeros((3, 3))

    def encode(self, tokens: list[str], file: list[str], grow: bool = False) -> list[list[int]]:
        rows = []
        for i, t in enumerate(tokens):
            named = [("own", f) for f in own_features(t)] + [("file", f) for f in file]
            for place, j in (("prev", i - 1), ("prev2", i - 2), ("next", i + 1)):
                if 0 <= j < len(tokens):
                    named += [(place, f) for f in side_features(tokens[j])]
            if grow:
                rows.append([self.index.setdefault(n, len(self.index)) for n in named])
            else:
                rows.append([self.index[n] for n in named if n in self.index])
        return rows

    def fit(self, lines: list[tuple[list[str], list[int], list[str]]], rounds: int = 60, rate: float = 0.1, ridge: float = 1e-3) -> Field:
        """Gradient steps (Adam) on the mean log likelihood; expectations by forward and backward sums over padded lines."""
        coded = [(self.encode(t, f, grow=True), y) for t, y, f in lines]
        n, most = len(coded), max(len(y) for _, y in coded)
        rows = np.concatenate([[i * most + j] * len(x) for i, (xs, _) in enumerate(coded) for j, x in enumerate(xs)]).astype(int)
        feats = np.concatenate([x for xs, _ in coded for x in xs]).astype(int)
        size = np.array([len(y) for _, y in coded])
        tags = np.full((n, most), O)
        for i, (_, y) in enumerate(coded):
            tags[i, : len(y)] = y
        real = np.arange(most)[None, :] < size[:, None]
        gold = np.eye(3)[tags] * real[..., None]
        pairs = np.zeros((3, 3))
        np.add.at(pairs, (tags[:, :-1][real[:, 1:]], tags[:, 1:][real[:, 1:]]), 1)
        w, tr = np.zeros((len(self.index), 3)), np.zeros((3, 3))
        state = [np.zeros_like(w), np.zeros_like(w), np.zeros_like(tr), np.zeros_like(tr)]

        def lse(x: np.ndarray, axis: int) -> np.ndarray:
            top = x.max(axis, keepdims=True)
            return (np.log(np.exp(x - top).sum(axis, keepdims=True)) + top).squeeze(axis)

        for step in range(1, rounds + 1):
            e = np.zeros((n * most, 3))
            np.add.at(e, rows, w[feats])
            e = e.reshape(n, most, 3)
            a, b = np.zeros_like(e), np.zeros_like(e)
            a[:, 0] = e[:, 0]
            for j in range(1, most):
                a[:, j] = lse(a[:, j - 1, :, None] + tr[None], 1) + e[:, j]
            for j in range(most - 2, -1, -1):
                b[:, j] = np.where(real[:, j + 1, None], lse(tr[None] + (e[:, j + 1] + b[:, j + 1])[:, None, :], 2), 0)
            z = lse(a[np.arange(n), size - 1], 1)
            p = np.exp(a + b - z[:, None, None]) * real[..., None]
            joint = np.exp(a[:, :-1, :, None] + tr[None, None] + (e + b)[:, 1:, None, :] - z[:, None, None, None]) * real[:, 1:, None, None]
            diff = ((gold - p).reshape(-1, 3))[rows]
            gw = np.zeros_like(w)
            np.add.at(gw, feats, diff)
            for x, g, m, v in ((w, gw / n - ridge * w, *state[:2]), (tr, (pairs - joint.sum((0, 1))) / n - ridge * tr, *state[2:])):
                m += 0.1 * (g - m)
                v += 0.01 * (g * g - v)
                x += rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
        self.w, self.trans = w, tr
        self._bounds()
        return self

    def _bounds(self) -> None:
        """How much file features and transitions could add to B or I over O, at most."""
        gain = {f: max(self.w[k][B], self.w[k][I]) - self.w[k][O] for (p, f), k in self.index.items() if p == "file"}
        turn = max(self.trans[a, y] - self.trans[a, O] for a in range(3) for y in (B, I)) + max(self.trans[y, c] - self.trans[O, c] for c in range(3) for y in (B, I))
        self.reach = sum(max(0.0, *(g for f, g in gain.items() if f in pair)) for pair in (("file:signs", "file:plain"), ("file:cue", "file:nocue"))) + max(0.0, turn)
        self.forms = _Forms(self)

    def __getstate__(self) -> dict:
        return {k: v for k, v in vars(self).items() if k != "forms"}

    def __setstate__(self, state: dict) -> None:
        vars(self).update(state)
        self.forms = _Forms(self)

    def own(self, token: str) -> np.ndarray:
        return sum((self.w[self.index["own", x]] for x in own_features(token) if ("own", x) in self.index), np.zeros(3))

    def form(self, token: str) -> int:
        """0: O in every best path unless beside a cue; 1: to be decoded; 2 more: a cue."""
        own = self.own(token)
        return int(max(own[B], own[I]) - own[O] + self.reach >= 0) + 2 * bool(side_features(token))

    def side(self, place: str, token: str) -> np.ndarray:
        return sum((self.w[self.index[place, x]] for x in side_features(token) if (place, x) in self.index), np.zeros(3))

    def viterbi(self, score: np.ndarray, first: np.ndarray, last: np.ndarray) -> list[int]:
        best, back = score[0] + first, []
        for e in score[1:]:
            step = best[:, None] + self.trans
            back.append(step.argmax(0))
            best = step.max(0) + e
        y = int((best + last).argmax())
        path = [y]
        for b in reversed(back):
            path.append(y := int(b[y]))
        return path[::-1]

    def spans(self, text: str) -> list[tuple[int, int]]:
        tokens = TOKEN.findall(text)
        form = np.frombuffer(bytes(map(self.forms.__getitem__, tokens)), np.uint8)
        cues = np.flatnonzero(form & 2)
        beside = (cues[:, None] + np.array([-1, 1, 2])).ravel()
        open_at = np.union1d(np.flatnonzero(form & 1), beside[(beside >= 0) & (beside < len(tokens))]).tolist()
        if not open_at:
            return []
        file = sum((self.w[self.index["file", f]] for f in file_features(text) if ("file", f) in self.index), np.zeros(3))
        places = None
        out = []
        lo = 0
        while lo < len(open_at):
            hi = lo + 1
            while hi < len(open_at) and open_at[hi] == open_at[hi - 1] + 1:
                hi += 1
            start, end = open_at[lo], open_at[hi - 1] + 1
            score = []
            for i in range(start, end):
                e = self.own(tokens[i]) + file
                for place, j in (("prev", i - 1), ("prev2", i - 2), ("next", i + 1)):
                    if 0 <= j < len(tokens):
                        e = e + self.side(place, tokens[j])
                score.append(e)
            # beside the piece stand tokens that are O in every best path
            path = self.viterbi(np.array(score), self.trans[O] if start else np.zeros(3), self.trans[:, O] if end < len(tokens) else np.zeros(3))
            if any(y != O for y in path):
                places = places or [m.span() for m in TOKEN.finditer(text)]
                for i, y in enumerate(path):
                    if y == B or (y == I and (i == 0 or path[i - 1] == O)):
                        out.append(list(places[start + i]))
                    elif y == I:
                        out[-1][1] = places[start + i][1]
            lo = hi
        return [tuple(s) for s in out]


@lru_cache(maxsize=1)
def field() -> Field:
    return Field().fit(generated())


def all_spans(text: str, model: Field) -> tuple[list[tuple[int, str, int]], list[tuple[int, str, int]]]:
    """Base spans, and those with the field's added."""
    base = base_spans(text)
    more = [(s, "crf", e) for s, e in model.spans(text) if not any(s < be and bs < e for bs, _, be in base)]
    return base, sorted(base + more, key=lambda x: (x[0], KINDS.index(x[1])))


def written(spans: list[tuple[int, str, int]]) -> str:
    return ",".join(f"{k}:{s}:{e}" for s, k, e in spans)


def secret_spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, base array<struct<kind,start,end>>, spans array<struct<kind,start,end>>) of every whole text."""
    ship(docs.sparkSession)
    model = field()
    span = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small(batches):
            found = [all_spans(t or "", model) for t in strings(b)]
            as_rows = [[[{"kind": k, "start": s, "end": e} for s, k, e in f[i]] for f in found] for i in (0, 1)]
            yield pa.RecordBatch.from_arrays([column(b, "doc_id"), pa.array(as_rows[0], span), pa.array(as_rows[1], span)], ["doc_id", "base", "spans"])

    kind = "array<struct<kind:string,start:long,end:long>>"
    return id_text(docs, id_col, text_col).mapInArrow(scan, f"doc_id long, base {kind}, spans {kind}")


def secret_digest(docs: DataFrame) -> DataFrame:
    from pyspark.sql import functions as F

    as_text = lambda c: F.array_join(F.transform(c, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")
    count = lambda k: F.size(F.filter("base", lambda s: s["kind"] == k)).cast("long").alias(f"n_{k}")
    found = secret_spans(docs)
    return found.select("doc_id", *map(count, KINDS[:3]), F.sha2(as_text("base"), 256).alias("base_sha256"), as_text("spans").alias("spans"))

