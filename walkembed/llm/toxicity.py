"""Toxicity by a Levenshtein automaton over a lexicon trie, with context windows.

The lexicon (given terms, plus word stems learned from labelled rows) is a trie.
Its product with a Levenshtein automaton is made deterministic, so one table
look-up a character follows every word of a batch at once; most words die after a
few.  Terms of 5 letters allow one edit, of 9 two, anywhere in the word; letters
with marks, look-alike digits and signs share their base letter's class.  Ordinary
words a few edits from a term, and such words of clean labelled rows, are spared.
Learned stems match exactly and accept any ending.

Each hit is weighed in its context window: inside quotation marks or beside words
of reporting it counts little, beside second-person words more.  A text's score
is 1 - exp(-scale * sum).  At the default scale one plain hit with one edit
decides a text; labelled rows move the scale either way where another cut serves
them better.

Fitting uses at most ``max_train_rows`` labelled rows a class and learns at most
``max_stems`` stems (documented bounds); scoring is one map over all texts.

Defined results: null, empty and clean texts score 0; repeated rows score alike;
null ids are returned; without toxic labels the given lexicon and the default
scale serve; extra columns are ignored.
"""

from __future__ import annotations

import re
import unicodedata
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .runtime import crc_bucket, labelled_sample
from .textkernel import Words, find_words, text_slices
from .workers import take_over

MAX_TRAIN_ROWS, MAX_STEMS = 2000, 64
THRESHOLD = 0.7
# The default lexicon.
TERMS = (
    "idiot", "moron", "stupid", "trash", "loser", "clown", "scum", "pathetic", "worthless", "disgusting",
    "imbecile", "bastard", "asshole", "retard", "dumbass", "scumbag", "bitch",
)
# Ordinary words and names within the edits of a default term.
ORDINARY = frozenset(
    "aitch apathetic batch bathetic birch blown boron botch brash butch closer crash crown dastard degusting digesting discussing disguising disrupting ditch"
    " doser fitch flown hitch idiom itch laser loger loner looser lose losen loses lover lower loyer mirthless mitch moon moran mormon morn morton oser petard"
    " pitch poser rash regard reward thrash trish witch wordless".split()
)
# Words of reporting and of address.
REPORTING = ("said", "says", "called", "calling", "quote", "quoted", "quoting", "word", "term", "wrote", "writes", "replied", "insult", "slur", "phrase")
ADDRESS = ("you", "your", "you're", "youre", "u", "ur", "yourself")
WINDOW = 6
FUZZY, QUOTED, ADDRESSED = 0.81, 0.25, 1.3  # SCALE * FUZZY reaches THRESHOLD
SCALE = 1.5
DEFAULT_CUT = float(-np.log(1 - THRESHOLD) / SCALE)
_LOOKALIKE = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "@": "a", "$": "s", "!": "i"}
_OPEN, _CLOSE = ('"', "'", "“", "‘", "«", "„", "`"), ('"', "'", "”", "’", "»", "“", "`")


# for lead bytes 0xC3 to 0xC9 and the byte behind, the ASCII base letter of a letter with marks
_BASE_LETTER = np.zeros(0x250, dtype=np.uint8)
for _code in range(0xC0, 0x250):
    _letter = unicodedata.normalize("NFD", chr(_code))[0]
    _BASE_LETTER[_code] = ord(_letter.lower()) if _letter.isascii() and _letter.isalpha() else 0
_SKIP = -1


def edits_allowed(term: str) -> int:
    return 0 if len(term) < 5 else 1 if len(term) < 9 else 2


@dataclass
class Lexicon:
    """Terms with weights; ``stems`` accept any ending; ``spared`` are exact words never matched by edits."""

    terms: dict[str, float] = field(default_factory=lambda: {t: 1.0 for t in TERMS})
    stems: dict[str, float] = field(default_factory=dict)
    spared: frozenset[str] = ORDINARY
    scale: float = SCALE


class Automaton:
    """Deterministic product of the lexicon's trie and the Levenshtein automaton, over classes of bytes."""

    def __init__(self, lexicon: Lexicon):
        entries = [(t.encode(), w, edits_allowed(t), False) for t, w in sorted(lexicon.terms.items())]
        entries += [(t.encode(), w, 0, True) for t, w in sorted(lexicon.stems.items())]
        entries = [e for e in entries if e[0]]
        used = sorted({b for e in entries for b in e[0]})
        self.byte_class = np.zeros(256, dtype=np.int64)
        for k, b in enumerate(used, 1):
            self.byte_class[b] = k
        for b in range(ord("A"), ord("Z") + 1):
            self.byte_class[b] = self.byte_class[b + 32]
        for sign, letter in _LOOKALIKE.items():
            self.byte_class[ord(sign)] = self.byte_class[ord(letter)]
        classes = len(used) + 1

        children: list[dict[int, int]] = [{}]
        ends: list[list[int]] = [[]]
        reach = [0]
        for i, (word, _, edits, _) in enumerate(entries):
            node = 0
            for b in word:
                c = int(self.byte_class[b])
                if c not in children[node]:
                    children[node][c] = len(children)
                    children.append({}), ends.append([]), reach.append(0)
                node = children[node][c]
                reach[node] = max(reach[node], edits)
            ends[node].append(i)

        def closed(items: dict[int, int]) -> frozenset[tuple[int, int]]:
            work = list(items.items())
            while work:
                node, e = work.pop()
                if e == items.get(node):
                    for child in children[node].values():  # a letter of the term left out
                        if e + 1 <= reach[child] and e + 1 < items.get(child, 99):
                            items[child] = e + 1
                            work.append((child, e + 1))
            return frozenset(items.items())

        def accepted(state: frozenset[tuple[int, int]]) -> tuple[float, int, int]:
            found = [(entries[i][1] * FUZZY**e, i, e) for node, e in state for i in ends[node] if not entries[i][3] and e <= entries[i][2]]
            return max(found, default=(0.0, -1, 0))

        reach[0] = max((e[2] for e in entries), default=0)
        start = closed({0: 0})
        names = {frozenset(): 0, start: 1}
        rows: list[np.ndarray] = [np.zeros(classes, dtype=np.int32)]
        weights, edits, sinks = [0.0], [0], [False]
        order = [start]
        for state in order:  # grows while it is walked
            row = np.zeros(classes, dtype=np.int32)
            stem = max((entries[i][1] for node, e in state if e == 0 for i in ends[node] if entries[i][3]), default=0.0)
            weight, _, e = accepted(state)
            weights.append(max(stem, weight)), edits.append(0 if stem >= weight else e), sinks.append(stem > 0)
            if not stem:
                for c in range(classes):
                    target: dict[int, int] = {}

                    def put(node: int, e: int, target: dict[int, int] = target) -> None:
                        if e <= reach[node] and e < target.get(node, 99):
                            target[node] = e

                    for node, e in state:
                        for letter, child in children[node].items():
                            if letter == c:
                                put(child, e)
                            else:
                                put(child, e + 1)
                        put(node, e + 1)
                    reached = closed(target)
                    if reached not in names:
                        names[reached] = len(names)
                        order.append(reached)
                    row[c] = names[reached]
            rows.append(row)
        self.table = np.stack(rows)
        self.weight, self.edits, self.sink = np.array(weights), np.array(edits), np.array(sinks)

    def classes(self, raw: np.ndarray) -> np.ndarray:
        """The class of every character at its first byte; combining marks and later bytes are skipped."""
        out = self.byte_class[raw]
        high = np.flatnonzero(raw >= 0x80)
        if not len(high):
            return out
        byte = raw[high].astype(np.int64)
        out[high[byte < 0xC0]] = _SKIP
        pair = (byte >= 0xC2) & (byte <= 0xCD) & (high + 1 < len(raw))
        at, lead = high[pair], byte[pair]
        code = ((lead & 0x1F) << 6) | (raw[at + 1] & 0x3F)
        letter = code < 0x250
        base = _BASE_LETTER[code[letter]]
        out[at[letter]] = np.where(base > 0, self.byte_class[base], 0)
        out[at[(code >= 0x300) & (code < 0x370)]] = _SKIP
        return out

    def match(self, raw: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(word index, weight, edits) of the words that the lexicon accepts."""
        at = np.flatnonzero(end > start)
        place, state = start[at], np.ones(len(at), dtype=np.int64)
        found: list[tuple[np.ndarray, np.ndarray]] = []
        classes = self.classes(raw)
        while len(at):
            letter = classes[place]
            state = np.where(letter == _SKIP, state, self.table[state, np.maximum(letter, 0)])
            place = place + 1
            over = (place == end[at]) | self.sink[state]
            hit = over & (self.weight[state] > 0)
            if hit.any():
                found.append((at[hit], state[hit]))
            alive = ~over & (state > 0)
            at, place, state = at[alive], place[alive], state[alive]
        if not found:
            none = np.empty(0, dtype=np.int64)
            return none, none.astype(float), none
        index, state = np.concatenate([f[0] for f in found]), np.concatenate([f[1] for f in found])
        order = np.argsort(index)
        return index[order], self.weight[state[order]], self.edits[state[order]]


_ALNUM = np.zeros(256, dtype=bool)
_ALNUM[list(b"0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz")] = True
_ALNUM[128:] = True


def trimmed(words: Words) -> tuple[np.ndarray, np.ndarray]:
    """Word borders without ASCII punctuation at either end."""
    inside = np.flatnonzero(_ALNUM[words.raw])
    if not len(inside):
        return words.start, words.start
    first = np.searchsorted(inside, words.start)
    last = np.searchsorted(inside, words.end) - 1
    some = last >= first
    lo = np.where(some, inside[np.minimum(first, len(inside) - 1)], words.start)
    hi = np.where(some, inside[np.maximum(last, 0)] + 1, words.start)
    # typographic quotes are three bytes beyond ASCII, the angle ones two
    for mark in ("“", "”", "„", "‘", "’", "«", "»"):
        code = np.frombuffer(mark.encode(), dtype=np.uint8)
        k = len(code)
        can = hi - lo > k
        if can.any():
            lead = can & np.all([words.raw[np.minimum(lo + j, len(words.raw) - 1)] == code[j] for j in range(k)], axis=0)
            lo = np.where(lead, lo + k, lo)
            tail = (hi - lo > k) & np.all([words.raw[np.maximum(hi - k + j, 0)] == code[j] for j in range(k)], axis=0)
            hi = np.where(tail, hi - k, hi)
    return lo, hi


def _context(words: Words, at: int, lo: int, hi: int) -> float:
    """The factor of a hit at word ``at`` of a text whose words are [lo, hi)."""
    a, b = max(lo, at - WINDOW), min(hi, at + WINDOW + 1)
    text = lambda k: words.raw[words.start[k] : words.end[k]].tobytes().decode("utf-8", "replace")
    around = [text(k) for k in range(a, b)]
    here = at - a
    factor = 1.0
    before = [i for i in range(here + 1) if around[i].startswith(_OPEN)]
    after = [i for i in range(here, len(around)) if around[i].rstrip(".,;:!?)").endswith(_CLOSE)]
    plain = [w.strip(".,;:!?\"'()“”„«»").lower() for w in around]
    if before and after and not any(around[i].rstrip(".,;:!?)").endswith(_CLOSE) for i in range(before[-1], here)):
        factor = QUOTED
    elif any(plain[i] in REPORTING for i in range(max(0, here - 3), min(len(plain), here + 3))):
        factor = QUOTED
    elif any(plain[i] in ADDRESS for i in range(max(0, here - 4), min(len(plain), here + 4))):
        factor = ADDRESSED
    return factor


def text_sums(words: Words, automaton: Automaton, spared: frozenset[str]) -> np.ndarray:
    """The weighted sum of hits of each text."""
    out = np.zeros(len(words.first) - 1)
    if not len(words.start):
        return out
    lo, hi = trimmed(words)
    index, weight, edits = automaton.match(words.raw, lo, hi)
    docs = np.searchsorted(words.first, index, side="right") - 1
    for k, w, e, d in zip(index.tolist(), weight.tolist(), edits.tolist(), docs.tolist()):
        if e and words.raw[lo[k] : hi[k]].tobytes().decode("utf-8", "replace").lower() in spared:
            continue
        out[d] += w * _context(words, k, int(words.first[d]), int(words.first[d + 1]))
    return out


_LETTERS = re.compile(r"[^\W\d_]+")


def learn_stems(texts: list[str], labels: list[int], known: Automaton, spared: frozenset[str], most: int = MAX_STEMS) -> dict[str, float]:
    """Word beginnings that mark toxic texts which the given terms do not decide: greedy cover by precise prefixes."""

    def prefixes(text: str) -> Counter:
        """How many distinct words of the text begin so."""
        return Counter(w[:k] for w in set(_LETTERS.findall(text.lower())) for k in range(3, min(len(w), 10) + 1))

    toxic, clean = [], Counter()
    for text, label in zip(texts, labels):
        if label:
            [(_, _, raw, offsets)] = list(text_slices(pa.array([text], pa.large_string())))
            if text_sums(find_words(raw, offsets), known, spared)[0] < DEFAULT_CUT:
                toxic.append(prefixes(text))
        else:
            clean.update(prefixes(text).keys())
    n_clean = max(1, len(labels) - sum(labels))
    stems: dict[str, float] = {}
    while toxic and len(stems) < most:
        count = Counter(p for s in toxic for p in s)
        least = max(3, round(0.02 * len(toxic)))
        words = Counter()
        for s in toxic:
            words.update(s)
        fit = [(c - clean[p], words[p], len(p), c, p) for p, c in count.items() if c >= least and clean[p] / n_clean <= 0.02 * c / max(1, len(toxic))]
        if not fit:
            break
        best = max(fit)[4]
        stems[best] = 1.0
        toxic = [s for s in toxic if best not in s]
    return stems


def fit(texts: list[str], labels: list[int], terms: tuple[str, ...] = TERMS, max_stems: int = MAX_STEMS) -> Lexicon:
    lexicon = Lexicon({t: 1.0 for t in terms})
    if not texts:
        return lexicon
    y = np.array(labels)
    first = Automaton(lexicon)
    near: set[str] = set()
    for lo, _, raw, offsets in text_slices(pa.array(texts, pa.large_string())):
        words = find_words(raw, offsets)
        if len(words.start):
            a, b = trimmed(words)
            index, _, edits = first.match(words.raw, a, b)
            docs = np.searchsorted(words.first, index, side="right") - 1
            for k, e, d in zip(index.tolist(), edits.tolist(), docs.tolist()):
                if e and not y[lo + d]:
                    near.add(words.raw[a[k] : b[k]].tobytes().decode("utf-8", "replace").lower())
    lexicon.spared |= near
    if y.any():
        lexicon.stems = learn_stems(texts, labels, first, lexicon.spared, max_stems)
    if y.any() and not y.all():
        # the cut with the best F1, of equal ones the nearest to the default, and the scale that puts it at the threshold
        automaton = Automaton(lexicon)
        sums = np.zeros(len(texts))
        for lo, hi, raw, offsets in text_slices(pa.array(texts, pa.large_string())):
            sums[lo:hi] = text_sums(find_words(raw, offsets), automaton, lexicon.spared)
        cuts = np.append(np.unique(np.clip(sums[sums > 0], 0.25, 3.0)), DEFAULT_CUT)
        f1 = np.array([2 * (y[sums >= c].sum()) / max(1, (sums >= c).sum() + y.sum()) for c in cuts])
        best = cuts[f1 == f1.max()]
        cut = best[np.argmin(np.abs(best - DEFAULT_CUT))]
        lexicon.scale = SCALE if cut == DEFAULT_CUT else float(-np.log(1 - THRESHOLD) / (cut * 0.999))
    return lexicon


def score_documents(docs: DataFrame, lexicon: Lexicon) -> DataFrame:
    """(doc_id, score) of every text."""
    shared = docs.sparkSession.sparkContext.broadcast((Automaton(lexicon), lexicon.spared, lexicon.scale))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        take_over("toxicity")
        automaton, spared, scale = shared.value
        for batch in batches:
            out = [1 - np.exp(-scale * text_sums(find_words(raw, offsets), automaton, spared)) for _, _, raw, offsets in text_slices(batch.column("text"))]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(np.concatenate(out) if out else [], pa.float64())], ["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, "doc_id long, score double")


def classify(docs: DataFrame, labels: DataFrame, held_out: tuple[int, int] | None = (3, 1), max_train_rows: int = MAX_TRAIN_ROWS, threshold: float = THRESHOLD) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every document."""
    lexicon = fit(*labelled_sample(docs, labels, "toxic", max_train_rows, held_out))
    away = crc_bucket("doc_id", held_out[0]) == held_out[1] if held_out else F.lit(False)
    return score_documents(docs, lexicon).select("doc_id", away.alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def keep(docs: DataFrame, lexicon: Lexicon, threshold: float = THRESHOLD) -> DataFrame:
    """The rows of ``docs`` that score below ``threshold``, with all their columns, in one map."""
    shared = docs.sparkSession.sparkContext.broadcast((Automaton(lexicon), lexicon.spared, lexicon.scale))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        take_over("toxicity")
        automaton, spared, scale = shared.value
        for batch in batches:
            parts = [1 - np.exp(-scale * text_sums(find_words(raw, offsets), automaton, spared)) < threshold for _, _, raw, offsets in text_slices(batch.column("text"))]
            yield batch.filter(pa.array(np.concatenate(parts) if parts else [], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
