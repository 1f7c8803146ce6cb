"""Secret spans: fixed patterns plus a linear-chain conditional random field.

Text is read as tokens: runs of value characters, or single other characters.
A token is tagged Begin, Inside or Outside of a secret.  Features of a token
are its shape class, the classes of its neighbours, whether a credential word
stands in the words before it, and features of the whole file.  Words without
a digit and of fewer than 24 characters are *plain*: the label set allows them
Outside only, and single marks may not Begin.  So every token between a plain
word and the next token that may Begin is Outside, and the chain over the
whole text falls apart, without approximation, into stretches that run from
such a token to the next plain word, Outside on either side.  Stretches have
no greatest length; Viterbi decoding of each, in linear time, is that of the text.

Weights are the maximum-likelihood ones (forward-backward gradients), learnt
from stretches of generated configuration lines and from stretches of a
bounded sample of the documents, tagged by the fixed patterns.  Spans of the
fixed patterns always stay; decoded spans that overlap none of them are added
under the kind ``crf``.

Edge cases: a null text counts as empty and has no spans; null ids stay;
repeated rows stay rows; extra columns are ignored (:func:`redact` keeps
them); an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import random
import re
from functools import lru_cache
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from delprop.llm.common import map_arrow

# Fixed patterns of the contract.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]{16,}")
HEX = re.compile(r"(?<![0-9a-f])[0-9a-f]{24,}")
KINDS = ("assign", "access", "hex")
CRF = "crf"

Span = tuple[int, int, int]

_TOKEN = re.compile(r"[A-Za-z0-9+/_.=-]+|[^\sA-Za-z0-9+/_.=-]")
#: What every token that may begin a secret holds.
_ODD = re.compile(r"[0-9]|[A-Za-z0-9+/_.=-]{24,}")
_LAST = re.compile(r"(?:[A-Za-z0-9+/_.=-]+|[^\sA-Za-z0-9+/_.=-])\Z")
_RUN = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_.=-")
_CREDENTIAL = re.compile(r"pass(word|wd|phrase)?|secret|token|api_?key|access_?key|private|credential|auth|bearer|signature", re.IGNORECASE)
SHAPES = ("plain", "word", "punct", "assign", "number", "phone", "dotted", "long_number", "hex", "hex_long", "mixed", "mixed_long", "base64", "mail", "uuid")
SHAPE = {name: i for i, name in enumerate(SHAPES)}
#: Words before a token in which a credential word is looked for.
REACH = 4
OUTSIDE, BEGIN, INSIDE = range(3)


def base_spans(text: str) -> list[Span]:
    """(start, kind, end) of the fixed patterns, sorted; code points."""
    out: list[Span] = []
    if "=" in text or ":" in text:
        out += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= 6]
    if "AKIA" in text:
        out += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text)]
    out += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(out)


@lru_cache(maxsize=1 << 14)
def shape(token: str) -> int:
    if token[0] not in _RUN:
        return SHAPE["punct"]
    core = token.strip("=-._/+")
    digits = sum(c.isdigit() for c in core)
    if not core:
        return SHAPE["assign" if "=" in token else "punct"]
    if re.fullmatch(r"[0-9a-fA-F]{8}(-[0-9a-fA-F]{4}){3}-[0-9a-fA-F]{12}", core):
        return SHAPE["uuid"]
    if digits == 0:
        if len(core) < 24:
            return SHAPE["plain"]
        mixed = core != core.lower() and core[1:] != core[1:].lower() and core != core.upper()
        return SHAPE["base64" if mixed else "word"]
    if core.isdigit():
        return SHAPE["number" if len(core) < 9 else "long_number"]
    if re.fullmatch(r"[0-9.,/:+-]+", core):
        return SHAPE["dotted" if "." in core else "phone"]
    if re.fullmatch(r"[0-9a-f]+|[0-9A-F]+", core):
        return SHAPE["hex_long" if len(core) >= 20 else "hex"]
    if re.search(r"\.[a-z]{2,}$", core):
        return SHAPE["mail"]
    if len(core) >= 16:
        kinds = (core != core.lower()) + (core != core.upper()) + (digits > 1)
        return SHAPE["base64" if kinds == 3 else "mixed_long"]
    return SHAPE["mixed"]


def file_class(text: str) -> int:
    """Features of the file: is it assignment-rich, is it digit-rich."""
    size = max(len(text), 1)
    return 2 * (text.count("=") * 200 > size) + (sum(text.count(d) for d in "0123456789") * 50 > size)


#: Feature blocks: own shape, previous shape, next shape, own shape x credential word near, own shape x file class.
_S = len(SHAPES)
_WIDTH = 3 * _S + 2 * _S + 4 * _S


def _words_before(text: str, at: int) -> list[str]:
    """The last ``REACH`` white-space separated words of ``text[:at]``, whole; the last one may touch ``at``."""
    size = 64
    while True:
        begin = max(0, at - size)
        words = text[begin:at].split()
        if begin == 0 or len(words) > REACH:
            return words[-REACH:]
        size *= 2


def stretches(text: str) -> list[tuple[list[tuple[int, int]], np.ndarray]]:
    """The stretches of the chain: their tokens' spans and feature indices (n x 5)."""
    found, out, seen = file_class(text), [], 0
    for hit in _ODD.finditer(text):
        if hit.start() < seen:
            continue
        left = hit.start()
        while left > seen and not text[left - 1].isspace():
            left -= 1
        tokens, shapes = [], []
        seen = len(text)
        for m in _TOKEN.finditer(text, left):
            kind = shape(m[0])
            if kind == SHAPE["plain"] and m.start() >= hit.end():
                seen = m.start()
                break
            tokens.append((m.start(), m.end()))
            shapes.append(kind)
        before = _words_before(text, left)
        flags = [False] * (REACH - len(before)) + [bool(_CREDENTIAL.search(w)) for w in before]
        prior = _LAST.search(before[-1]) if before else None
        previous = shape(prior[0]) if prior else SHAPE["plain"]
        rows = []
        for i, ((a, b), s) in enumerate(zip(tokens, shapes, strict=True)):
            near = any(flags[-REACH:])
            p = shapes[i - 1] if i else previous
            n = shapes[i + 1] if i + 1 < len(shapes) else SHAPE["plain"]
            rows.append((s, _S + p, 2 * _S + n, 3 * _S + 2 * s + near, 5 * _S + 4 * s + found))
            flags.append(bool(_CREDENTIAL.search(text, a, b)))
        out.append((tokens, np.array(rows, np.int64)))
    return out


class Chain:
    """Weights of the field and its two recursions; plain words and single marks may not begin a secret, and a stretch is Outside on either side."""

    def __init__(self) -> None:
        self.unary = np.zeros((_WIDTH, 3))
        self.step = np.zeros((3, 3))

    def scores(self, rows: np.ndarray) -> np.ndarray:
        out = self.unary[rows].sum(1)
        out[rows[:, 0] == SHAPE["plain"], 1:] = -np.inf
        out[np.isin(rows[:, 0], (SHAPE["punct"], SHAPE["assign"])), BEGIN] = -np.inf
        return out

    def _transition(self) -> np.ndarray:
        step = self.step.copy()
        step[OUTSIDE, INSIDE] = -np.inf
        return step

    def viterbi(self, rows: np.ndarray) -> list[int]:
        scores, step = self.scores(rows), self._transition()
        best = step[OUTSIDE] + scores[0]
        back = []
        for s in scores[1:]:
            through = best[:, None] + step
            back.append(through.argmax(0))
            best = through.max(0) + s
        tags = [int((best + step[:, OUTSIDE]).argmax())]
        for b in reversed(back):
            tags.append(int(b[tags[-1]]))
        return tags[::-1]

    def fit(self, data: list[tuple[np.ndarray, list[int]]], turns: int = 60, rate: float = 0.3, decay: float = 1e-3) -> Chain:
        """Adagrad on the exact log-likelihood, over grouped equal stretches."""
        grouped: dict[bytes, list] = {}
        for rows, tags in data:
            held = grouped.setdefault(rows.tobytes() + bytes(tags), [rows, tags, 0])
            held[2] += 1
        total = sum(h[2] for h in grouped.values())
        squares = [np.full_like(x, 1e-8) for x in (self.unary, self.step)]
        for _ in range(turns):
            grads = [decay * self.unary, decay * self.step]
            for rows, tags, times in grouped.values():
                self._gradient(rows, tags, times / total, grads)
            for value, grad, square in zip((self.unary, self.step), grads, squares, strict=True):
                square += grad**2
                value -= rate * grad / np.sqrt(square)
        return self

    def _gradient(self, rows: np.ndarray, tags: list[int], weight: float, grads: list[np.ndarray]) -> None:
        scores, step = self.scores(rows), self._transition()
        n = len(scores)
        ahead, behind = np.empty((n, 3)), np.empty((n, 3))
        with np.errstate(invalid="ignore"):
            ahead[0], behind[-1] = step[OUTSIDE] + scores[0], step[:, OUTSIDE]
            for i in range(1, n):
                ahead[i] = np.logaddexp.reduce(ahead[i - 1][:, None] + step, 0) + scores[i]
            for i in range(n - 2, -1, -1):
                behind[i] = np.logaddexp.reduce(step + (scores[i + 1] + behind[i + 1])[None, :], 1)
            norm = np.logaddexp.reduce(ahead[-1] + behind[-1])
            single = np.nan_to_num(np.exp(ahead + behind - norm))
        single[np.arange(n), tags] -= 1
        for block in rows.T:
            np.add.at(grads[0], block, weight * single)
        grads[1][OUTSIDE] += weight * single[0]
        grads[1][:, OUTSIDE] += weight * single[-1]
        for i in range(1, n):
            with np.errstate(invalid="ignore"):
                pair = np.nan_to_num(np.exp(ahead[i - 1][:, None] + step + (scores[i] + behind[i])[None, :] - norm))
            pair[tags[i - 1], tags[i]] -= 1
            grads[1] += weight * pair


def tagged(text: str, spans: list[tuple[int, int]]) -> list[tuple[np.ndarray, list[int]]]:
    """Training stretches of a text whose secret values are ``spans``."""
    out = []
    for tokens, rows in stretches(text):
        tags, held = [], None
        for a, b in tokens:
            owner = next(((x, y) for x, y in spans if a < y and x < b), None)  # few spans: training texts only
            if owner is None or rows[len(tags), 0] == SHAPE["plain"]:
                tags.append(OUTSIDE)
            elif owner == held:
                tags.append(INSIDE)
            else:
                tags.append(BEGIN if rows[len(tags), 0] not in (SHAPE["punct"], SHAPE["assign"]) else OUTSIDE)
            held = owner if tags[-1] != OUTSIDE else None
        out.append((rows, tags))
    return out


def generated(count: int = 400, seed: int = 7) -> list[tuple[str, list[tuple[int, int]]]]:
    """Labelled lines of configuration and prose, with secrets and with harmless look-alikes."""
    draw = random.Random(seed)

    def of(letters: str, low: int, high: int) -> str:
        return "".join(draw.choice(letters) for _ in range(draw.randint(low, high)))

    small, large, ten = "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789"
    secret = [lambda: of(ten + "abcdef", 32, 64), lambda: of(ten + "ABCDEF", 32, 64), lambda: of(small + large + ten, 24, 48), lambda: "AKIA" + of(large + ten, 16, 16), lambda: of(small + large + ten + "+/", 28, 60)]
    harmless = [
        lambda: of(ten, 1, 6), lambda: of(ten, 12, 19), lambda: ".".join(str(draw.randint(0, 255)) for _ in range(4)), lambda: f"+1 ({of(ten, 3, 3)}) {of(ten, 3, 3)}-{of(ten, 4, 4)}",
        lambda: f"{of(small, 3, 9)}.{of(ten, 1, 3)}@{of(small, 3, 8)}{of(ten, 1, 1)}.{of(small, 4, 8)}.com", lambda: "-".join(of(ten + "abcdef", k, k) for k in (8, 4, 4, 4, 12)),
        lambda: f"{of(small, 2, 6)}{of(ten, 1, 3)}", lambda: f"{of(ten, 4, 4)}-{of(ten, 2, 2)}-{of(ten, 2, 2)}", lambda: of(ten + "abcdef", 6, 8), lambda: "/".join(of(small + ten, 3, 8) for _ in range(4)) + ".html",
    ]
    names = ["secret key", "API key", "access_key", "auth token", "password", "bearer", "private key", "signature", "passphrase"]
    out = []
    for _ in range(count):
        words = [of(small, 2, 10) for _ in range(draw.randint(3, 9))]
        at = draw.randint(0, len(words))
        kind = draw.random()
        head = " ".join(words[:at] + ([draw.choice(names) + draw.choice([" ", ": ", " = ", " is ", '="'])] if kind < 0.4 else [""]))
        value = draw.choice(secret if kind < 0.5 else harmless)()
        text = head + value + draw.choice(["", ".", '"', "!!"]) + " " + " ".join(words[at:])
        out.append((text, [(len(head), len(head) + len(value))] if kind < 0.5 else []))
    return out


def train(documents: DataFrame, sample_rows: int = 400) -> Chain:
    """Fit on generated lines and on a bounded, hash-spread sample of documents that hold a long odd token."""
    odd = documents.select("doc_id", "text").where(F.col("text").rlike(r"[0-9]{3}"))
    # thinned by a hash of the row, so that the driver gets about sample_rows texts whatever the number of tasks
    keep = min(1.0, sample_rows / max(odd.count(), 1))
    spread = F.pmod(F.xxhash64(F.lit("secrets"), "doc_id", "text"), F.lit(1 << 30)) < F.lit(int(keep * (1 << 30)))
    rows = odd.where(spread).select("text").collect()
    data = [x for line, spans in generated() for x in tagged(line, spans)]
    for (body,) in sorted(rows):
        # values only: the pattern's key and quotes are context
        spans = [(m.start(2), m.end(2)) for m in ASSIGN.finditer(body) if len(m[2]) >= 6] + [(a, b) for a, kind, b in base_spans(body) if kind]
        data += tagged(body, spans)
    return Chain().fit(data)


def crf_spans(text: str, chain: Chain) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for tokens, rows in stretches(text):
        tags = chain.viterbi(rows)
        for (a, b), tag in zip(tokens, tags, strict=True):
            if tag == BEGIN:
                out.append((a, b))
            elif tag == INSIDE and out:
                out[-1] = (out[-1][0], b)
    return out


def find(text: str, chain: Chain) -> tuple[list[Span], list[tuple[int, int]]]:
    """Fixed spans, and decoded spans that overlap none of them."""
    base = base_spans(text)
    extra, k = [], 0
    reach = list(accumulate((y for _, _, y in base), max))
    for a, b in crf_spans(text, chain):
        while k < len(base) and base[k][0] < b:
            k += 1
        # base spans that start before b; one of them overlaps if the furthest end lies beyond a
        if not k or reach[k - 1] <= a:
            extra.append((a, b))
    return base, extra


def _joined(spans: list[Span]) -> str:
    return ",".join(f"{(*KINDS, CRF)[k]}:{a}:{b}" for a, k, b in spans)


def scan(documents: DataFrame, chain: Chain) -> DataFrame:
    """(doc_id, n_assign, n_access, n_hex, base_sha256, spans) for every row of ``documents``."""

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        counts, digests, spans = [[], [], []], [], []
        for text in batch.column("text").to_pylist():
            base, extra = find(text or "", chain)
            for k in range(3):
                counts[k].append(sum(kind == k for _, kind, _ in base))
            digests.append(hashlib.sha256(_joined(base).encode()).hexdigest())
            spans.append(_joined(sorted(base + [(a, 3, b) for a, b in extra])))
        columns = [batch.column("doc_id"), *(pa.array(c, pa.int64()) for c in counts), pa.array(digests, pa.string()), pa.array(spans, pa.string())]
        return pa.record_batch(columns, ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"])

    rows = documents.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return map_arrow(rows, kernel, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string")


def masked(text: str, chain: Chain, mark: str = "[SECRET]") -> str:
    base, extra = find(text, chain)
    out, at = [], 0
    for a, b in sorted([(a, b) for a, _, b in base] + extra):
        if a >= at:
            out += [text[at:a], mark]
        at = max(at, b)
    return "".join([*out, text[at:]])


def redact(documents: DataFrame, chain: Chain) -> DataFrame:
    """``documents`` with every secret span replaced by a mark, and n_chars (if there) counted anew; all rows and columns stay."""

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        new = [None if t is None else masked(t, chain) for t in batch.column("text").to_pylist()]
        for name, values in (("text", new), ("n_chars", [None if t is None else len(t) for t in new])):
            if name in batch.schema.names:
                at = batch.schema.get_field_index(name)
                batch = batch.set_column(at, batch.schema.field(at), pa.array(values, batch.schema.field(at).type))
        return batch

    return map_arrow(documents, kernel, documents.schema)
