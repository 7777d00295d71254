"""Secret scans: fixed patterns, and character Markov models of random strings and of ordinary identifiers.

Every run of ``[A-Za-z0-9+/_=-]`` with 16 characters or more is scored by the log-likelihood ratio of two models of second
order (each character given the two before it, with interpolated smoothing), trained from labelled samples. Runs whose mean ratio
reaches the threshold become spans of kind ``markov``; the patterns' own spans always stay. Matching is done on whole texts
in Python workers, batch by batch; nothing is shuffled.

Null and empty texts have no spans, texts of any length are scanned whole, an empty table gives no rows. Repeated rows give repeated results. Extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import batches_of, documents, sha256_hex

#: The contract's patterns (fixed values), in the order in which kinds are listed.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{16,}")
KINDS = ("assign", "access", "hex", "markov")
KEYWORDS = ("password", "passwd", "secret", "token", "api_key", "apikey")
RUN = re.compile(r"[A-Za-z0-9+/_=-]{16,}")
ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=-"
#: Nats a character above which a run counts as random.
THRESHOLD = 0.6
#: Most labelled samples of each kind that are used.
MAX_SAMPLES = 20_000


# ---------------------------------------------------------------- labelled samples
def random_samples(n: int = 4000) -> list[str]:
    """Strings drawn from hex, base-62 and base-64 alphabets by a counter run through SHA-256: the same on every machine."""
    sets = ("0123456789abcdef", ALPHABET[:62], ALPHABET[:64], ALPHABET[:26] + ALPHABET[52:62], ALPHABET[26:62])
    out = []
    for i in range(n):
        digest = b"".join(hashlib.sha256(b"%d-%d" % (i, j)).digest() for j in range(2))
        letters = sets[i % len(sets)]
        out.append("".join(letters[d % len(letters)] for d in digest[: 16 + i % 33]))
    return out


def identifier_samples(words: list[str], n: int = 4000) -> list[str]:
    """Ordinary identifiers and paths: words joined as code, paths and plain prose join them."""
    words = sorted({w for w in words if re.fullmatch(r"[A-Za-z]{2,}", w)})
    if not words:
        return []
    out = []
    for i in range(n):
        d = hashlib.sha256(b"id%d" % i).digest()
        picked = [words[int.from_bytes(d[2 * k : 2 * k + 2], "big") % len(words)].lower() for k in range(3 + i % 4)]
        style = i % 6
        if style == 0:
            out.append("_".join(picked))
        elif style == 1:
            out.append(picked[0] + "".join(w.title() for w in picked[1:]))
        elif style == 2:
            out.append("-".join(picked))
        elif style == 3:
            out.append("/".join(picked) + str(i % 10))
        elif style == 4:
            out.append("_".join(picked).upper())
        else:
            out.append("".join(picked))
    return out


# ---------------------------------------------------------------- the models
class MarkovRatio:
    """Log-likelihood ratio of a string under two character models."""

    def __init__(self, table: np.ndarray):
        self.table = table  # [before-last, last, next]

    @staticmethod
    def codes(s: str) -> np.ndarray:
        return _CODE[np.frombuffer(s.encode("ascii"), np.uint8)]

    @classmethod
    def train(cls, random: list[str], ordinary: list[str]) -> "MarkovRatio":
        a = len(ALPHABET) + 1

        def logs(samples: list[str]) -> np.ndarray:
            full = np.zeros((a, a, a))
            for s in samples[:MAX_SAMPLES]:
                c = np.concatenate([[0, 0], cls.codes(s)])
                np.add.at(full, (c[:-2], c[1:-1], c[2:]), 1)
            one = full.sum((0, 1)) + 0.5
            one /= one.sum()
            two = full.sum(0)
            two = (two + 5 * one) / (two.sum(-1, keepdims=True) + 5)
            return np.log((full + 5 * two) / (full.sum(-1, keepdims=True) + 5))

        return cls((logs(random) - logs(ordinary)).astype(np.float64))

    def mean(self, s: str) -> float:
        c = np.concatenate([[0, 0], self.codes(s)])
        return float(self.table[c[:-2], c[1:-1], c[2:]].sum() / len(s)) if s else 0.0


_CODE = np.zeros(256, np.int64)
_CODE[np.frombuffer(ALPHABET.encode(), np.uint8)] = np.arange(1, len(ALPHABET) + 1)


# ---------------------------------------------------------------- spans
def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind number, end) of the fixed patterns, ordered by start, then kind."""
    found = []
    folded = text.lower()
    if any(k in folded for k in KEYWORDS):
        found += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= 12]
    if "AKIA" in text:
        found += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 18]
    found += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(found)


def markov_spans(text: str, model: MarkovRatio, threshold: float, known: dict[str, bool]) -> list[tuple[int, int, int]]:
    found = []
    for m in RUN.finditer(text):
        s = m[0]
        verdict = known.get(s)
        if verdict is None:
            if len(known) > 200_000:
                known.clear()
            verdict = known[s] = model.mean(s) >= threshold
        if verdict:
            found.append((m.start(), 3, m.end()))
    return found


def written(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in spans)


SCHEMA = "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_markov long"


def scan(docs: DataFrame, model: MarkovRatio, threshold: float = THRESHOLD) -> DataFrame:
    """Spans of every document."""

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[str, bool] = {}
        for b in batches_of(it):
            rows = []
            for doc_id, text in zip(b.column("doc_id").to_pylist(), b.column("text").to_pylist()):
                base = base_spans(text or "")
                more = markov_spans(text or "", model, threshold, known)
                n = [sum(k == kind for _, k, _ in base) for kind in range(3)]
                rows.append((doc_id, *n, sha256_hex(written(base).encode()), written(sorted(base + more)), len(more)))
            c = list(zip(*rows))
            yield pa.RecordBatch.from_arrays([*(pa.array(x, pa.int64()) for x in c[:4]), pa.array(c[4], pa.string()), pa.array(c[5], pa.string()), pa.array(c[6], pa.int64())], names=["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_markov"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, SCHEMA)


def labelled_samples(spark: SparkSession, sf_dir: str) -> tuple[list[str], list[str]]:
    """Random strings, and identifiers joined from at most ``MAX_SAMPLES`` distinct words of the benchmark, those of the smallest hashes."""
    words = spark.read.parquet(f"{sf_dir}/benchmark.parquet").select(F.explode(F.split("text", r"[^A-Za-z]+")).alias("w")).filter(F.length("w") > 1).distinct().orderBy(F.xxhash64("w"), "w").limit(MAX_SAMPLES)
    return random_samples(), identifier_samples([r[0] for r in words.collect()])


def op3_markov_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(documents(spark, sf_dir), MarkovRatio.train(*labelled_samples(spark, sf_dir)))
