"""Secret scan: fixed patterns, and character Markov models compared by log-likelihood ratio.

Three base patterns give spans of their own.  Beyond them, every long run of
token characters is scored by two order-2 character models, of random strings and
of ordinary identifiers, trained from labelled samples.  Where the mean
log-likelihood ratio a character of a window of ``MIN_MODEL`` characters passes a
cut calibrated on the samples, the part of the windows that stands out most, in
whole words of letters and digits, becomes a span of kind ``model`` unless a base
span meets it.

Every base match of the access and hex kinds lies inside a run of token
characters, so one pass finds the runs and the rest looks only inside them.

Defined results: null and empty texts have no spans; repeated rows repeat; null
ids are returned; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .workers import take_over

# The base kinds in their order, the least lengths, and the patterns.
KINDS = ("assign", "access", "hex", "model")
MIN_ASSIGN, MIN_ACCESS, MIN_HEX, MIN_MODEL = 12, 18, 16, 20
_KEYWORD = re.compile(r"password|passwd|secret|token|api_?key", re.IGNORECASE | re.ASCII)
_ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
_RUN = re.compile(r"[A-Za-z0-9+/_=-]{16,}")
_ACCESS = re.compile(r"AKIA[A-Z0-9]+")
_HEX = re.compile(r"[0-9a-f]{16,}")
REDACTED = "[SECRET]"

Span = tuple[int, int, str]

# Everyday words that identifiers are made of.
WORDS = (
    "account address application array average background balance batch blueprint buffer button calendar category channel "
    "client cluster collection column command comment commit complete component config connection container content context "
    "counter create customer database default delete description device directory document download element employee encode "
    "english entity entry error example export feature field filter folder format function gateway generate government group "
    "handler header history identifier image import index information input instance integer internal invoice keyboard label "
    "language layout library license listener local manager message method middle model module network notification number "
    "object operation option order output package parameter parent partition password pattern payment permission picture "
    "position preview process product profile project property provider query question random record reference region register "
    "release report request resource response result schedule schema screen search section security select server service "
    "session setting shipment signal source standard state statistics status storage street string student subject summary "
    "support system table target template thread ticket title transaction transfer translation update upload user validate "
    "value variable version video visitor warehouse warning widget window workflow "
    "nicht werden durch einheit verordnung gesellschaft entwicklung wissenschaft leistung sicherheit "
    "information developpement gouvernement changement nouvelle mouvement quelque universite "
    "desarrollo informacion gobierno generalmente comunidad rapidamente nacional estacion"
).split()
# Syllables of the languages that texts are written in.
SYLLABLES = (
    "the ion tion an er re th ing st en ti on es or ha nd ou ed at to is ble le ly ea de ment os ado che ver ung keit lich heit schaft ein ge sch "
    "pf tz dampf schiff fahrt werk haus land stadt rechts que eur euse elle ique aux ant cia dad mente cion ria que ando ista ness ful able inter con "
    "pro com per ana tri uni mono graph logie"
).split()


def labelled_samples(seed: int = 17) -> list[tuple[str, int]]:
    """(string, 1 for random or 0 for ordinary), made by rule from a fixed seed."""
    rng = np.random.default_rng(seed)
    lower, upper, digits = "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789"
    alphabets = [digits + "abcdef", digits + "ABCDEF", upper + digits, upper + lower + digits, upper + lower + digits + "+/", upper + lower + digits + "_-", lower, upper + lower, lower + digits]
    out = [("".join(rng.choice(list(alphabets[k % len(alphabets)]), int(rng.integers(MIN_MODEL, 48)))), 1) for k in range(1500)]
    for k in range(1500):
        picked = rng.choice(WORDS, int(rng.integers(2, 6))).tolist()
        tail = ["", "", str(rng.integers(0, 100)), str(rng.integers(1990, 2030)), f"v{rng.integers(1, 9)}"][k % 5]
        style = k % 8
        if style == 0:
            text = "_".join([*picked, *([tail] if tail else [])])
        elif style == 1:
            text = picked[0] + "".join(w.title() for w in picked[1:]) + tail
        elif style == 2:
            text = "-".join([*picked, *([tail] if tail else [])])
        elif style == 3:
            text = "/".join([*picked, *([tail] if tail else [])])
        elif style == 4:
            text = "_".join(picked).upper() + ("_" + tail.upper() if tail else "")
        elif style == 5:
            text = "".join(picked) + tail
        elif style == 6:  # words as languages compound them
            text = "".join(rng.choice(SYLLABLES, int(rng.integers(6, 14))))
            text = text.title() if k % 3 else text
        elif k % 16 < 8:  # rules
            text = str(rng.choice(list("-=_+/x0"))) * int(rng.integers(MIN_MODEL, 60))
        else:  # dates and numbers
            text = "-/_"[k % 3].join(str(n) for n in rng.integers(1, 2030, 8))
        out.append((text, 0))
    return out


_SIZE = 68  # 26 + 26 + 10 characters, "+/_=-", and one for all others
_CODE = np.full(256, _SIZE - 1, dtype=np.int64)
for _k, _c in enumerate(b"abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789+/_=-"):
    _CODE[_c] = _k


class MarkovRatio:
    """Log-likelihood ratio a character of two order-2 models with backed-off smoothing."""

    def __init__(self, samples: list[tuple[str, int]] | None = None, smooth: float = 4.0):
        samples = labelled_samples() if samples is None else samples
        tables = []
        for label in (1, 0):
            pair = np.full((_SIZE, _SIZE), 0.1)
            triple = np.zeros((_SIZE, _SIZE, _SIZE))
            for text, k in samples:
                if k == label:
                    c = _CODE[np.frombuffer(text.encode(), dtype=np.uint8)]
                    np.add.at(pair, (c[:-1], c[1:]), 1)
                    np.add.at(triple, (c[:-2], c[1:-1], c[2:]), 1)
            lower = pair / pair.sum(1, keepdims=True)
            tables.append(np.log((triple + smooth * lower[None]) / (triple.sum(2, keepdims=True) + smooth)))
        self.ratio = (tables[0] - tables[1]).astype(np.float32)
        scores = [(self(text), label) for text, label in samples if len(text) >= MIN_MODEL]
        random, plain = np.array([s for s, k in scores if k]), np.array([s for s, k in scores if not k])
        # between almost all ordinary and almost all random samples
        self.cut = max(0.0, float((np.quantile(plain, 0.999) + np.quantile(random, 0.01)) / 2)) if len(random) and len(plain) else np.inf

    def windows(self, text: str) -> np.ndarray:
        """The mean ratio of every window of ``MIN_MODEL`` characters; of the whole text, if it is shorter."""
        c = _CODE[np.frombuffer(text.encode(), dtype=np.uint8)]
        if len(c) < 3:
            return np.full(1, -np.inf)
        run = np.concatenate([[0.0], np.cumsum(self.ratio[c[:-2], c[1:-1], c[2:]], dtype=np.float64)])
        size = min(MIN_MODEL - 2, len(run) - 1)
        return (run[size:] - run[:-size]) / size

    def __call__(self, text: str) -> float:
        return float(self.windows(text).max())

    def spans(self, text: str) -> list[tuple[int, int]]:
        """The random parts of a run: of joined windows above the cut the part that stands out most, in whole words."""
        joined: list[list[int]] = []
        for lo in np.flatnonzero(self.windows(text) > self.cut).tolist():
            if joined and lo <= joined[-1][1]:
                joined[-1][1] = lo + MIN_MODEL
            else:
                joined.append([lo, lo + MIN_MODEL])
        out: list[tuple[int, int]] = []
        for lo, hi in joined:
            c = _CODE[np.frombuffer(text[lo:hi].encode(), dtype=np.uint8)]
            run = np.concatenate([[0.0], np.cumsum(self.ratio[c[:-2], c[1:-1], c[2:]] - self.cut)])
            low = np.minimum.accumulate(run)
            stop = int((run - low).argmax())
            begin = int(run[: stop + 1].argmin())
            begin, stop = lo + begin + 2 * (begin > 0), lo + stop + 2  # a ratio is about the third of its characters
            while begin and text[begin - 1].isalnum():
                begin -= 1
            while stop < len(text) and text[stop].isalnum():
                stop += 1
            if out and begin < out[-1][1]:
                out[-1] = out[-1][0], max(stop, out[-1][1])
            else:
                out.append((begin, stop))
        return out


def base_spans(text: str, runs: list[tuple[int, int]]) -> list[Span]:
    spans: list[Span] = []
    if _KEYWORD.search(text):
        spans += [(*m.span(), "assign") for m in _ASSIGN.finditer(text) if m.end(2) - m.start(2) >= MIN_ASSIGN]
    for lo, hi in runs:
        spans += [(*m.span(), "access") for m in _ACCESS.finditer(text, lo, hi) if m.end() - m.start() >= MIN_ACCESS]
        spans += [(*m.span(), "hex") for m in _HEX.finditer(text, lo, hi) if m.end() - m.start() >= MIN_HEX]
    return sorted(spans, key=lambda s: (s[0], KINDS.index(s[2])))


def find_spans(text: str, model: MarkovRatio) -> tuple[list[Span], list[Span]]:
    """(base spans, all spans) of a text, each sorted by start and kind."""
    runs = [m.span() for m in _RUN.finditer(text)]
    base = base_spans(text, runs)
    more = []
    for lo, hi in runs:
        if hi - lo >= MIN_MODEL:
            near = [(a, b) for a, b, _ in base if a < hi and lo < b]
            more += [(lo + a, lo + b, "model") for a, b in model.spans(text[lo:hi]) if not any(c < lo + b and lo + a < d for c, d in near)]
    return base, sorted(base + more, key=lambda s: (s[0], KINDS.index(s[2])))


def joined(spans: list[Span]) -> str:
    return ",".join(f"{kind}:{lo}:{hi}" for lo, hi, kind in spans)


def _scan(docs: DataFrame, schema: str | T.StructType, make: Callable[[pa.RecordBatch, list], pa.RecordBatch]) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        take_over("secrets")
        model = MarkovRatio()
        for batch in batches:
            yield make(batch, [find_spans(t, model) if t else ([], []) for t in (x.as_py() for x in batch.column("text"))])

    return docs.mapInArrow(run, schema)


def scan(docs: DataFrame) -> DataFrame:
    """(doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_model) of every text."""

    def make(batch: pa.RecordBatch, found: list[tuple[list[Span], list[Span]]]) -> pa.RecordBatch:
        number = lambda kind: pa.array([sum(s[2] == kind for s in spans) for _, spans in found], pa.int64())
        digest = [hashlib.sha256(joined(base).encode()).hexdigest() for base, _ in found]
        return pa.RecordBatch.from_arrays([batch.column("doc_id"), number("assign"), number("access"), number("hex"), pa.array(digest, pa.string()), pa.array([joined(spans) for _, spans in found], pa.string()), number("model")], ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_model"])

    schema = "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_model long"
    return _scan(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), schema, make)


def blanked(text: str, spans: list[Span]) -> str:
    """The text with every span (overlapping ones as one) replaced by a marker."""
    parts, at = [], 0
    for lo, hi, _ in spans:
        if lo >= at:
            parts += [text[at:lo], REDACTED]
        at = max(at, hi)
    return "".join([*parts, text[at:]])


def redact(docs: DataFrame) -> DataFrame:
    """``docs`` with the secrets of ``text`` blanked and ``n_chars`` brought up to date; null texts stay null."""

    def make(batch: pa.RecordBatch, found: list[tuple[list[Span], list[Span]]]) -> pa.RecordBatch:
        old = batch.column("text").to_pylist()
        texts = [t if t is None or not spans else blanked(t, spans) for t, (_, spans) in zip(old, found)]
        columns = dict(zip(batch.schema.names, batch.columns))
        columns["text"] = pa.array(texts, batch.schema.field("text").type)
        if "n_chars" in columns:
            kept = columns["n_chars"].to_pylist()
            columns["n_chars"] = pa.array([len(t) if spans and t is not None else n for t, n, (_, spans) in zip(texts, kept, found)], batch.schema.field("n_chars").type)
        return pa.RecordBatch.from_arrays(list(columns.values()), list(columns))

    return _scan(docs, docs.schema, make)
