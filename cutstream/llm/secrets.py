"""Secret scanning: fixed patterns, plus a character convolutional network over every candidate and its context.

Spans of the three base kinds (assign, access, hex) always stay. Every other candidate, a run of 16 or more token
characters with a letter and a digit, one of 20 or more with small and capital letters, or a value after a credential word, is scored by a small network in numpy: learned
character vectors, one convolution over 24 characters of left context, the candidate and 16 of right context, pooled
apart over the context and over the candidate. Where a base span overlaps a candidate, the parts outside are candidates;
overlapping candidates are all scored, and those that are secrets become one span. A candidate longer than the window is scored window by window and keeps
its highest score. The network is fitted on labelled findings made from stated formats (`labelled`, a bounded number),
its scores are calibrated on findings it has not seen, and its threshold is the highest that keeps the wanted recall
there. Fitting is seeded and takes a few seconds on the driver; the weights (about 20 KB) go to the tasks.

Null text: empty, no spans. Spans are code points, end exclusive, per kind leftmost and non-overlapping. Repeated rows
give equal results.
"""

from __future__ import annotations

import hashlib
import random
import re
import string
from bisect import bisect_right
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cutstream.llm.common import batched

KINDS = ("assign", "access", "hex", "generic")
#: Fixed patterns of the base kinds, as the contract states them; the last number is the least length that counts.
ASSIGN = re.compile(r"([Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy])[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)")
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
RUN = re.compile(r"[A-Za-z0-9+/_=-]{16,}")
#: Fixed credential words of the network's second kind of candidate.
CREDENTIAL = re.compile(r"(?:pwd|passphrase|bearer|credential|private_?key|auth_?key)[\"']?\x20*[:=]?\x20*[\"']?([A-Za-z0-9+/_.=-]{8,})", re.IGNORECASE | re.ASCII)
#: The same at every place, so that a credential word inside another's value has a value too.
_CREDENTIAL_AT = re.compile(f"(?={CREDENTIAL.pattern})", CREDENTIAL.flags)
_ASSIGN_WORDS = ("passw", "secret", "token", "api")
_CREDENTIAL_WORDS = ("pwd", "passphrase", "bearer", "credential", "private", "auth")

LEFT, BODY, RIGHT, WIDTH, FILTERS, DIM, HIDDEN = 24, 56, 16, 5, 24, 8, 16
LENGTH = LEFT + BODY + RIGHT
FINDINGS, RECALL, SEED = 3000, 0.98, 7


def base_spans(text: str) -> list[tuple[int, int, str]]:
    out = []
    low = text.lower()
    if any(w in low for w in _ASSIGN_WORDS):
        out += [(m.start(), m.end(), "assign") for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 6]
    if "AKIA" in text:
        out += [(m.start(), m.end(), "access") for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    out += [(m.start(), m.end(), "hex") for m in HEX.finditer(text)]
    return out


def candidates(text: str, taken: list[tuple[int, int, str]]) -> list[tuple[int, int]]:
    """Spans for the network, which may overlap each other: those of its patterns, and of each what no base span covers."""
    base = merged([(a, b) for a, b, _ in taken])
    found = {s for m in RUN.finditer(text) for s in _outside(*m.span(), base, 16) if _mixed(text[slice(*s)])}
    low = text.lower()
    if any(w in low for w in _CREDENTIAL_WORDS):
        found |= {s for m in _CREDENTIAL_AT.finditer(text) for s in _outside(*m.span(1), base, 8)}
    return sorted(found)


def _mixed(run: str) -> bool:
    """Whether a run has letters and digits, or is long and has letters of both cases."""
    if any(c.isdigit() for c in run):
        return any(c.isalpha() for c in run)
    return len(run) >= 20 and not run.islower() and not run.isupper() and any(c.islower() for c in run)


def _outside(a: int, b: int, base: list[tuple[int, int]], least: int) -> list[tuple[int, int]]:
    """The parts of a to b, of at least `least` characters, that no span of base (sorted, disjoint) covers."""
    out = []
    for i in range(bisect_right(base, a, key=lambda s: s[1]), len(base)):
        x, y = base[i]
        if x >= b:
            break
        out.append((a, x))
        a = y
    return [(x, y) for x, y in [*out, (a, b)] if y - x >= least]


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Spans that overlap as one, so that nothing that a candidate covers stays outside."""
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a < out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def windows(text: str, a: int, b: int) -> list[tuple[str, int]]:
    """(LENGTH characters, length of the candidate's part) of each window over a candidate."""
    return [(text[max(0, s - LEFT) : s].rjust(LEFT, "\0") + text[s : min(b, s + BODY)].ljust(BODY, "\0") + text[min(b, s + BODY) : min(b, s + BODY) + RIGHT].ljust(RIGHT, "\0"), min(b - s, BODY)) for s in range(a, b, BODY)]


def codes(parts: list[str]) -> np.ndarray:
    """Characters as small numbers: 0 none, printable ASCII 1 to 95, white space as a blank, 96 anything else."""
    flat = np.frombuffer("".join(parts).encode("utf-32-le", "surrogatepass"), "<u4").reshape(len(parts), LENGTH)
    return np.where(flat == 0, 0, np.where((flat >= 32) & (flat < 127), flat - 31, np.where((flat >= 9) & (flat < 14), 1, 96))).astype(np.int64)


class Network:
    """Character vectors, one convolution with ReLU, maxima and means over context and candidate, two dense layers."""

    def __init__(self, seed: int):
        r = np.random.default_rng(seed)
        norm = lambda *s, n: (r.standard_normal(s) * np.sqrt(2 / n)).astype(np.float32)
        self.p = {"e": norm(97, DIM, n=DIM), "k": norm(WIDTH * (DIM + 1), FILTERS, n=WIDTH * (DIM + 1)), "kb": np.zeros(FILTERS, np.float32), "w": norm(3 * FILTERS, HIDDEN, n=3 * FILTERS), "wb": np.zeros(HIDDEN, np.float32), "o": norm(HIDDEN, n=HIDDEN), "ob": np.zeros(1, np.float32)}
        self.scale, self.shift, self.threshold = 1.0, 0.0, 0.5

    def forward(self, x: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, tuple]:
        p, at = self.p, np.arange(LENGTH)
        inside = ((at >= LEFT) & (at < LEFT + n[:, None])).astype(np.float32)
        h = np.concatenate([p["e"][x] * (x > 0)[..., None], inside[..., None]], axis=2)
        steps = LENGTH - WIDTH + 1
        cols = np.concatenate([h[:, i : i + steps] for i in range(WIDTH)], axis=2)
        conv = np.maximum(cols @ p["k"] + p["kb"], 0)
        body = inside[:, WIDTH // 2 : WIDTH // 2 + steps]
        near, own = conv * (1 - body)[..., None], conv * body[..., None]
        f = np.concatenate([near.max(1), own.max(1), own.sum(1) / np.maximum(body.sum(1), 1)[:, None]], axis=1)
        z = np.maximum(f @ p["w"] + p["wb"], 0)
        return z @ p["o"] + p["ob"], (x, cols, conv, body, near, own, f, z)

    def gradients(self, kept: tuple, d: np.ndarray) -> dict[str, np.ndarray]:
        p, (x, cols, conv, body, near, own, f, z) = self.p, kept
        g = {"o": z.T @ d, "ob": d.sum(keepdims=True)}
        dz = d[:, None] * p["o"] * (z > 0)
        g |= {"w": f.T @ dz, "wb": dz.sum(0)}
        df = dz @ p["w"].T
        dc = np.broadcast_to((df[:, 2 * FILTERS :] / np.maximum(body.sum(1), 1)[:, None])[:, None] * body[..., None], conv.shape).copy()
        i, j = np.arange(len(x))[:, None], np.arange(FILTERS)
        np.add.at(dc, (i, near.argmax(1), j), df[:, :FILTERS])
        np.add.at(dc, (i, own.argmax(1), j), df[:, FILTERS : 2 * FILTERS])
        dc *= conv > 0
        g |= {"k": cols.reshape(-1, cols.shape[2]).T @ dc.reshape(-1, FILTERS), "kb": dc.sum((0, 1))}
        dcols = dc @ p["k"].T
        de, steps = np.zeros((len(x), LENGTH, DIM), np.float32), cols.shape[1]
        for s in range(WIDTH):
            de[:, s : s + steps] += dcols[:, :, s * (DIM + 1) : s * (DIM + 1) + DIM]
        g["e"] = np.zeros_like(p["e"])
        np.add.at(g["e"], x, de * (x > 0)[..., None])
        return g

    def scores(self, parts: list[tuple[str, int]]) -> np.ndarray:
        """Calibrated probability of each window."""
        out = [np.zeros(0)]
        for i in range(0, len(parts), 512):
            own = parts[i : i + 512]
            z, _ = self.forward(codes([w for w, _ in own]), np.array([n for _, n in own]))
            out.append(1 / (1 + np.exp(-np.clip(self.scale * z.astype(np.float64) + self.shift, -30, 30))))
        return np.concatenate(out)


def labelled(n: int, seed: int) -> list[tuple[str, int, int, bool]]:
    """n labelled findings (text, start, end, secret?): half secrets of many formats, half look-alikes, in prose."""
    r = random.Random(seed)
    pick = lambda chars, a, b: "".join(r.choice(chars) for _ in range(r.randint(a, b)))
    low, alnum, b64 = string.ascii_lowercase, string.ascii_letters + string.digits, string.ascii_letters + string.digits + "+/"
    word = lambda a=2, b=9: pick(low, a, b)
    prose = lambda: " ".join(word().capitalize() if r.random() < 0.1 else word() for _ in range(r.randint(2, 8)))
    secret = [
        lambda: pick(alnum, 20, 64), lambda: pick(b64, 30, 60) + r.choice(["", "=", "=="]), lambda: word(2, 4) + "_" + pick(alnum, 24, 40),
        lambda: word(2, 3) + "_live_" + pick(alnum, 20, 32), lambda: "-".join([word(3, 5), pick(string.digits, 8, 12), pick(alnum, 20, 28)]),
        lambda: "eyJ" + pick(alnum + "_-", 40, 120), lambda: pick("0123456789abcdef", 16, 23), lambda: pick(string.ascii_uppercase + string.digits, 18, 40),
        lambda: pick(string.ascii_letters, 22, 44),
    ]
    names = ["key", "pwd", "passphrase", "bearer", "credential", "private_key", "auth_key", "access", "pass", "client"]
    plain = [
        lambda: "_".join(word() for _ in range(r.randint(3, 5))) + r.choice("0123456789"), lambda: "/".join(word() for _ in range(r.randint(3, 6))) + "/" + pick(string.digits, 1, 4),
        lambda: "-".join(pick("0123456789abcdef", k, k) for k in (8, 4, 4, 4, 12)), lambda: pick("=-_", 1, 1) * r.randint(16, 40) + "a1", lambda: word(8, 9) + word(8, 9) + str(r.randint(1, 2030)),
        lambda: f"{r.randint(1990, 2030)}-{r.randint(1, 12):02}-{r.randint(1, 28):02}T{r.randint(0, 23):02}-{r.randint(0, 59):02}", lambda: "".join(word(3, 8).capitalize() for _ in range(4)) + str(r.randint(0, 99)),
        lambda: "your_" + word(3, 6) + "_goes_here_" + str(r.randint(1, 9)), lambda: r.choice("xX0") * r.randint(16, 30) + "1a", lambda: word(3, 6) + "-" + "-".join(str(r.randint(0, 99)) for _ in range(5)) + "-" + word(3, 6),
        lambda: word(5, 9) + "/" + word(5, 9) + "_" + pick(string.digits, 4, 8), lambda: "".join(word(3, 9).capitalize() for _ in range(r.randint(4, 6))),
        lambda: word(4, 8) + "".join(word(4, 9).capitalize() for _ in range(3)), lambda: "/".join(word(3, 9).capitalize() for _ in range(4)), lambda: "-".join(word(3, 9).capitalize() for _ in range(4)),
    ]
    out = []
    for i in range(n):
        real = i % 2 == 0
        value = r.choice(secret if real else plain)()
        lead = r.choice([f"{r.choice(names)} = \"", f"{r.choice(names)}: ", f"{r.choice(names).upper()}=", "", ""]) if real else r.choice(["see ", "id: ", "", "", "/", "file ", "name = \""])
        before = prose() + r.choice([" ", "\n", " ("]) + lead
        out.append((before + value + r.choice(['"', " ", ".", ",", ")", "\n"]) + prose(), len(before), len(before) + len(value), real))
    r.shuffle(out)
    return out


@lru_cache(maxsize=4)
def fitted(findings: int = FINDINGS, recall: float = RECALL, seed: int = SEED, rounds: int = 6) -> Network:
    """A network fitted on `findings` labelled findings and calibrated on half as many others."""
    net, rng = Network(seed), np.random.default_rng(seed)

    def arrays(rows: list[tuple[str, int, int, bool]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        first = [windows(t, a, b)[0] for t, a, b, _ in rows]
        return codes([w for w, _ in first]), np.array([n for _, n in first]), np.array([y for *_, y in rows], np.float32)

    x, n, y = arrays(labelled(findings, seed))
    m1, m2 = ({k: np.zeros_like(v) for k, v in net.p.items()} for _ in range(2))
    step = 0
    for _ in range(rounds):
        order = rng.permutation(len(x))
        for i in range(0, len(order), 64):
            b = order[i : i + 64]
            z, kept = net.forward(x[b], n[b])
            grads = net.gradients(kept, ((1 / (1 + np.exp(-z)) - y[b]) / len(b)).astype(np.float32))
            step += 1
            for k, g in grads.items():
                m1[k] = 0.9 * m1[k] + 0.1 * g
                m2[k] = 0.999 * m2[k] + 0.001 * g * g
                net.p[k] = (net.p[k] - 0.004 * (m1[k] / (1 - 0.9**step)) / (np.sqrt(m2[k] / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
    x, n, y = arrays(labelled(findings // 2, seed + 1))
    z = net.forward(x, n)[0].astype(np.float64)
    a, b = 1.0, 0.0
    for _ in range(50):  # logistic calibration by damped Newton steps, with a small penalty that keeps it finite
        p = 1 / (1 + np.exp(-np.clip(a * z + b, -30, 30)))
        w = p * (1 - p) + 1e-9
        grad = np.array([((p - y) * z).sum() + 0.01 * (a - 1), (p - y).sum()])
        hess = np.array([[(w * z * z).sum() + 0.01, (w * z).sum()], [(w * z).sum(), w.sum() + 1e-6]])
        d = np.linalg.solve(hess, grad)
        a, b = a - 0.5 * d[0], b - 0.5 * d[1]
    net.scale, net.shift = float(a), float(b)
    scores = np.sort(1 / (1 + np.exp(-np.clip(a * z[y > 0] + b, -30, 30))))
    net.threshold = float(max(0.5, scores[int((1 - recall) * len(scores))]))  # recall first, but never below an even chance
    if (scores >= net.threshold).mean() < recall:
        net.threshold = float(scores[int((1 - recall) * len(scores))])
    return net


def find(texts: list[str], net: Network) -> list[list[tuple[int, int, str]]]:
    """All spans of each text, by start, then kind in the order of KINDS."""
    base = [base_spans(t) for t in texts]
    parts, owner = [], []
    for i, t in enumerate(texts):
        for a, b in candidates(t, base[i]):
            for w in windows(t, a, b):
                parts.append(w)
                owner.append((i, a, b))
    found: dict[int, list[tuple[int, int]]] = {}
    for i, a, b in dict.fromkeys(o for o, s in zip(owner, net.scores(parts).tolist(), strict=True) if s >= net.threshold):
        found.setdefault(i, []).append((a, b))
    for i, spans in found.items():
        base[i] += [(a, b, "generic") for a, b in merged(spans)]
    return [sorted(x, key=lambda s: (s[0], KINDS.index(s[2]))) for x in base]


def _said(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for a, b, k in spans)


def scan(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_generic of every row; map-only."""
    net = spark.sparkContext.broadcast(fitted())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, texts in batched(batches):
            found = find(texts, net.value)
            counts = [pa.array([sum(s[2] == k for s in x) for x in found], pa.int64()) for k in KINDS]
            base = [hashlib.sha256(_said([s for s in x if s[2] != "generic"]).encode()).hexdigest() for x in found]
            yield pa.RecordBatch.from_arrays([rows.column("doc_id"), *counts[:3], pa.array(base), pa.array([_said(x) for x in found]), counts[3]], ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_generic"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_generic long")


def redacted(text: str, spans: list[tuple[int, int, str]], mark: str = "[SECRET]") -> str:
    out, at = [], 0
    for a, b, _ in spans:
        if a >= at:
            out += [text[at:a], mark]
        at = max(at, b)
    return "".join([*out, text[at:]])


def redact(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """docs with every secret replaced by a mark and n_chars (where it is a column) counted again; columns as they were."""
    net, names = spark.sparkContext.broadcast(fitted()), docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, texts in batched(batches):
            spans = find(texts, net.value)
            given = rows.column("text").to_pylist()
            new = [None if g is None else redacted(t, s) for g, t, s in zip(given, texts, spans, strict=True)]
            cols = {c: rows.column(c) for c in names}
            cols["text"] = pa.array(new, pa.string())
            if "n_chars" in cols:
                changed = [len(x) if s else n for x, s, n in zip(new, spans, cols["n_chars"].to_pylist(), strict=True)]
                cols["n_chars"] = pa.array(changed, cols["n_chars"].type)
            yield pa.RecordBatch.from_arrays(list(cols.values()), names)

    return docs.mapInArrow(run, docs.schema)


def op4_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Secrets of every document."""
    return scan(spark, spark.read.parquet(f"{sf_dir}/documents.parquet"))
