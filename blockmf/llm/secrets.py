"""Secret scan: fixed patterns, and a linear-chain conditional random field for secrets that no pattern knows.

Base patterns (kinds assign, access, hex) are found leftmost and non-overlapping per kind in the whole text. The field
tags the tokens of a line as secret begin, inside or outside (B, I, O) from the token's shape, length and mixture of
characters, its neighbouring words, and two features of the file (how much of it looks like code, how many digits it has);
Viterbi decoding gives the spans (kind crf). A span that overlaps a base span is not added: base spans stay.

Only tokens that could be a secret (at least eight characters of the secret alphabet, with digits among other characters) may be B or I: that is a
constraint of the field, so lines without such a token decode to O throughout and are not built. The field is trained
here, by gradient ascent on the exact log-likelihood (forward-backward), on lines made from a seed by templates:
assignments, tokens in prose, urls, dates, numbers, phone numbers, version strings and plain words.

Edge cases. Null or empty text: no spans. Offsets count code points, ends are exclusive. Very long texts: scanned whole; lines
longer than `LINE` tokens are decoded in overlapping windows. Repeated rows: one result each. Empty table: empty result.
"""

from __future__ import annotations

import bisect
import hashlib
import re
import zlib
from collections.abc import Iterator
from functools import lru_cache
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# The base patterns of the contract, with the least lengths of what they match.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
KINDS = ("assign", "access", "hex", "crf")
LEAST_VALUE, LEAST_ACCESS = 6, 20

KEYWORDS = frozenset("password passwd pwd pass secret token key apikey api_key auth bearer credential credentials login access private client session signature cert passphrase".split())
_TOKEN = re.compile(r"[A-Za-z0-9+/_.=\-]+|[^\sA-Za-z0-9+/_.=\-]", re.A)
_ABLE = re.compile(r"(?=[^0-9]*[0-9])(?=[^A-Za-z]*[A-Za-z])[A-Za-z0-9+/_.=\-]{8,}", re.A)
_DIGITS = re.compile(r"[0-9]+", re.A)
_CODE = re.compile(r"[{};=<>()\[\]]")
B, I, O = 0, 1, 2
WIDTH, LINE = 4096, 256


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind number, end)."""
    found = [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= LEAST_VALUE]
    found += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= LEAST_ACCESS]
    found += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(found)


def able(token: str) -> bool:
    return len(token) >= 8 and _ABLE.fullmatch(token) is not None


@lru_cache(maxsize=65536)
def shape(token: str) -> str:
    """Runs of character classes of the whole token, squeezed: the first ten, and about how many there are."""
    out = []
    for c in token:
        k = "d" if c.isdigit() else "a" if c.islower() else "A" if c.isupper() else c if c in "=/+_-.:\"'" else "x"
        if not out or out[-1] != k:
            out.append(k)
    return "".join(out[:10]) + f"{min(len(out) // 8, 9)}"


@lru_cache(maxsize=65536)
def word_features(token: str) -> tuple[str, ...]:
    n = len(token)
    digits = sum(map(str.isdigit, token)) / n
    upper = sum(map(str.isupper, token)) / n
    turns = sum(a.isdigit() != b.isdigit() or a.isupper() != b.isupper() for a, b in zip(token, token[1:], strict=False)) / n
    kinds = len(set(token)) / n
    return (
        f"len{min(n // 4, 12)}",
        f"dig{int(digits * 5)}",
        f"up{int(upper * 5)}",
        f"turn{int(turns * 6)}",
        f"kinds{int(kinds * 5)}",
        f"able{able(token)}",
        f"dots{min(token.count('.') + token.count('/'), 4)}",
        f"dash{min(token.count('-'), 4)}",
        f"w:{token.lower() if token.lower() in KEYWORDS or n < 3 else '-'}",
        f"turnlen{int(turns * 4)}.{min(n // 8, 4)}",
    )


def file_features(text: str) -> tuple[str, str]:
    n = len(text) or 1
    code = len(_CODE.findall(text)) / n
    digits = sum(map(text.count, "0123456789")) / n
    return f"code{min(int(code * 50), 3)}", f"fdig{min(int(digits * 20), 3)}"


@lru_cache(maxsize=262144)
def _slot(name: str) -> int:
    return zlib.crc32(name.encode()) % WIDTH


def line_features(tokens: list[str], of_file: tuple[str, str]) -> list[list[int]]:
    """Feature slots of each token."""
    rows = []
    for i, t in enumerate(tokens):
        names = [*word_features(t), f"s:{shape(t)}" if len(t) > 2 else "s:-"]
        for d in (-3, -2, -1, 1):
            if 0 <= i + d < len(tokens):
                w = tokens[i + d].lower()
                names.append(f"{d}:{w if w in KEYWORDS or len(w) == 1 and not w.isalnum() else 'able' if able(tokens[i + d]) else 'word'}")
            else:
                names.append(f"{d}:edge")
        names += [f"{of_file[0]}|{able(t)}", f"{of_file[1]}|{able(t)}", "bias"]
        rows.append([_slot(x) for x in names])
    return rows


_EDGES = np.zeros((3, 3))
_EDGES[O, I] = -1e4  # inside only after begin or inside
_START = np.array([0.0, -1e4, 0.0])
_UNABLE = np.array([-1e4, -1e4, 0.0])


def _scores(weights: np.ndarray, tokens: list[str], of_file: tuple[str, str]) -> np.ndarray:
    emit = np.array([weights[r].sum(0) for r in line_features(tokens, of_file)])
    for i, t in enumerate(tokens):
        if not able(t):
            emit[i] += _UNABLE
    return emit


def viterbi(emit: np.ndarray, trans: np.ndarray) -> list[int]:
    best, back = emit[0] + _START, []
    for e in emit[1:]:
        all_ = best[:, None] + trans + _EDGES
        back.append(all_.argmax(0))
        best = all_.max(0) + e
    tags = [int(best.argmax())]
    for b in reversed(back):
        tags.append(int(b[tags[-1]]))
    return tags[::-1]


# --- training --------------------------------------------------------------------------------------------------------


def _made_lines(n: int, seed: int) -> list[tuple[list[str], list[int], tuple[str, str]]]:
    """Lines of tokens with tags, from templates."""
    rng = np.random.default_rng(seed)
    low, up, dig = "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789"
    pick = lambda s, k: "".join(rng.choice(list(s), k))
    word = lambda: "".join(rng.choice(["an", "th", "er", "on", "ti", "re", "ion", "le", "en", "st", "ou", "ge", "ver", "ing", "é", "ñ", "ble", "co"], int(rng.integers(1, 5))))

    def secret() -> str:
        for _ in range(50):
            kind = rng.integers(6)
            k = int(rng.integers(16, 44))
            s = (pick(low + up + dig, k), pick(low + dig, k), pick(up + dig, k), pick(low + up + dig + "+/", k) + "=" * int(rng.integers(3)), pick(["sk", "pk", "ghp", "xoxb", "pat"], 1) + rng.choice(["_", "-"]) + pick(low + up + dig, k), "-".join(pick(low + up + dig, 8) for _ in range(3)))[kind]
            if able(s):
                return s
        return "Zx9" + pick(dig, 9)

    def plain() -> str:
        kind = rng.integers(12)
        return (
            word(), word(), word(), word() + rng.choice([",", "."]), str(rng.integers(10**9)), f"20{rng.integers(10, 40)}-{rng.integers(1, 13):02d}-{rng.integers(1, 29):02d}T{rng.integers(10, 24)}.{rng.integers(10, 60)}",
            f"v{rng.integers(20)}.{rng.integers(20)}.{rng.integers(99)}-rc{rng.integers(9)}", f"www.{word()}{rng.integers(99)}.example.org/{word()}/{rng.integers(9999)}", f"{word()}_{word()}_{rng.integers(99)}", f"IMG_{rng.integers(10**6)}.jpg", f"+{rng.integers(99)}-{rng.integers(10**6)}-{rng.integers(10**4)}", f"{word()}.{word()}{rng.integers(999)}",
        )[kind]

    out = []
    for _ in range(n):
        line: list[tuple[str, int]] = [(plain(), 0) for _ in range(int(rng.integers(0, 7)))]
        r = rng.random()
        if r < 0.45:
            if rng.random() < 0.7:
                line.append((str(rng.choice(sorted(KEYWORDS))) + str(rng.choice([":", " =", "=", " is", ""])) + rng.choice(["", '"', " '"]), 0))
            line.append((secret(), 1))
        elif r < 0.55:
            line.append((str(rng.choice(sorted(KEYWORDS))), 0))
        line += [(plain(), 0) for _ in range(int(rng.integers(0, 7)))]
        tokens, tags = [], []
        for text, is_secret in line:
            parts = _TOKEN.findall(text)
            tokens += parts
            tags += [B if is_secret and able(p) and k == 0 else I if is_secret and able(p) else O for k, p in enumerate(parts)]
        if tokens:
            out.append((tokens[:40], tags[:40], file_features(" ".join(t for t, _ in line) + " " + word() * 30)))
    return out


@lru_cache(maxsize=1)
def train(n: int = 3000, seed: int = 17, rounds: int = 60, rate: float = 0.5, ridge: float = 1e-4) -> tuple[np.ndarray, np.ndarray]:
    """(feature weights, tag transitions): full-batch gradient ascent with momentum of the exact log-likelihood; lines of one length go together."""
    lines = _made_lines(n, seed)
    by_length: dict[int, list] = {}
    for tokens, tags, of_file in lines:
        by_length.setdefault(len(tokens), []).append((line_features(tokens, of_file), tags, [not able(t) for t in tokens]))
    groups = [(np.array([x[0] for x in g]), np.array([x[1] for x in g]), np.array([x[2] for x in g])) for g in by_length.values()]
    w, t = np.zeros((WIDTH, 3)), np.zeros((3, 3))
    vw, vt = np.zeros_like(w), np.zeros_like(t)
    g2w = np.full_like(w, 1e-8)
    for _ in range(rounds):
        gw, gt = -ridge * len(lines) * w, -ridge * len(lines) * t
        for feats, tags, unable in groups:
            m, length = tags.shape
            emit = w[feats].sum(2) + unable[:, :, None] * _UNABLE
            full = t + _EDGES
            fwd = np.empty((length, m, 3))
            fwd[0] = emit[:, 0] + _START
            for i in range(1, length):
                fwd[i] = np.logaddexp.reduce(fwd[i - 1][:, :, None] + full, axis=1) + emit[:, i]
            back = np.zeros((length, m, 3))
            for i in range(length - 2, -1, -1):
                back[i] = np.logaddexp.reduce(full[None] + (emit[:, i + 1] + back[i + 1])[:, None, :], axis=2)
            z = np.logaddexp.reduce(fwd[-1], axis=1)
            prob = np.exp(fwd + back - z[None, :, None])
            hot = np.eye(3)[tags]
            diff = hot - prob.transpose(1, 0, 2)
            np.add.at(gw, feats.reshape(-1), np.repeat(diff.reshape(-1, 3), feats.shape[2], 0))
            for i in range(1, length):
                pair = np.exp(fwd[i - 1][:, :, None] + full + (emit[:, i] + back[i])[:, None, :] - z[:, None, None])
                gt += np.einsum("na,nb->ab", hot[:, i - 1], hot[:, i]) - pair.sum(0)
        g2w = 0.9 * g2w + 0.1 * gw**2
        vw = 0.8 * vw + 0.2 * gw / np.sqrt(g2w + 1e-6)
        vt = 0.8 * vt + 0.2 * gt / len(lines)
        w, t = w + rate * 0.2 * vw, t + rate * vt
    return w, t


# --- scan ------------------------------------------------------------------------------------------------------------


def field_spans(text: str, weights: np.ndarray, trans: np.ndarray) -> list[tuple[int, int]]:
    """(start, end) of the secrets that the field finds."""
    found, done, of_file = [], -1, None
    for m in _DIGITS.finditer(text):  # a token that is able has a digit
        if m.start() < done:
            continue
        a, b = text.rfind("\n", 0, m.start()) + 1, text.find("\n", m.start())
        b = len(text) if b < 0 else b
        done = b
        places = [x.span() for x in _TOKEN.finditer(text, a, b)]
        tokens = [text[s:e] for s, e in places]
        if not any(map(able, tokens)):
            continue
        of_file = of_file or file_features(text)
        for lo in range(0, len(tokens), LINE - 8):  # windows that overlap by the reach of the features
            part = tokens[lo : lo + LINE]
            if not any(map(able, part)):
                continue
            tags = viterbi(_scores(weights, part, of_file), trans)
            for k, tag in enumerate(tags):
                s, e = places[lo + k]
                if tag == B and (not found or s >= found[-1][1]):
                    found.append((s, e))
                elif tag == I and found and s - found[-1][1] <= 1 and s >= found[-1][1]:
                    found[-1] = (found[-1][0], e)
    return found


def scan(text: str, weights: np.ndarray, trans: np.ndarray) -> tuple[list[tuple[int, int, int]], list[tuple[int, int, int]]]:
    """(base spans, all spans), each (start, kind number, end) in order."""
    base = base_spans(text)
    every = list(base)
    starts, reach = [x for x, _, _ in base], list(accumulate((y for _, _, y in base), max))
    for s, e in field_spans(text, weights, trans):
        before = bisect.bisect_left(starts, e)  # base spans that start before the end; the farthest end of them tells whether one overlaps
        if not before or reach[before - 1] <= s:
            every.append((s, 3, e))
    return base, sorted(every)


def show(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in spans)


_OUT = ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"]


def _scan_batches(weights: np.ndarray, trans: np.ndarray):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for text in b.column(1):
                base, every = scan(text.as_py() or "", weights, trans)
                kinds = [k for _, k, _ in base]
                rows.append((kinds.count(0), kinds.count(1), kinds.count(2), hashlib.sha256(show(base).encode()).hexdigest(), show(every)))
            cols = list(zip(*rows, strict=True)) if rows else [[]] * 5
            kinds_ = [pa.int64()] * 3 + [pa.string()] * 2
            yield pa.RecordBatch.from_arrays([b.column(0), *[pa.array(c, k) for c, k in zip(cols, kinds_, strict=True)]], _OUT)

    return run


def find_secrets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans: one row per row of docs. Texts are independent: nothing is shuffled."""
    weights, trans = train()
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(_scan_batches(weights, trans), f"doc_id {dict(rows.dtypes)['doc_id']}, n_assign long, n_access long, n_hex long, base_sha256 string, spans string")
