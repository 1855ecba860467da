"""Toxicity: noisy-channel deobfuscation, then scoring of the restored text.

Words written with digits or signs for letters, with letters repeated or spaced apart, are lattices of what may have been
meant. Viterbi search under a character language model (smoothed n-grams, mixed with whole known words) picks the most
likely reading, each substitution, dropped repetition and closed gap at its own cost. Gaps are arcs of the lattice: over a
run of short fragments each gap is closed or ends a word. Signs at a word's limits may also be what they are. Where nothing
but doubled letters or signs at the end speak for another reading, only a known word is one. Texts are scored by the
evidence of their restored words.

The language model is counted over the texts of all documents, labelled or not, and grows with them; only the evidence and
its calibration come from a bounded sample of labelled rows (``SAMPLE``). Scores read nothing but text.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field
from functools import cached_property, lru_cache
from hashlib import md5
from itertools import chain, groupby, product, repeat
from operator import itemgetter
from zlib import crc32

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cardest.llm.common import stored

#: Labelled training rows that evidence is fitted on, by hash of the identifier; the language model has no such bound.
SAMPLE = 20_000
#: Words or word beginnings with evidence kept at most.
FEATURES = 50_000
#: Distinct words or features a counting task holds before it hands partial counts on.
HELD = 500_000
#: What a sign may stand for, in natural order.
SIGNS = {
    "0": "o", "1": "il", "2": "z", "3": "e", "4": "a", "5": "s", "6": "g", "7": "t", "8": "b", "9": "g",
    "@": "a", "$": "s", "!": "i", "|": "il", "+": "t", "€": "e", "(": "c",
}
#: Log costs of a substitution, of a dropped repeated letter, of a closed gap and of signs that are themselves.
COST = {"sign": -0.7, "repeat": -0.3, "gap": -0.2, "literal": -3.0}
ORDER = 3
#: Share of the whole-word part in the language model.
WORD_SHARE = 0.5
BEAM = 32
#: Fixed value: log cost of a shorter history.
_BACK = math.log(0.4)
#: Lengths of word beginnings that are evidence of their own.
STEMS = (4, 5, 6, 7)

_SIGNS = "".join(SIGNS)
_SIGN = "".join(map(re.escape, SIGNS))
_WORD = re.compile(r"[^\W\d_]+")
_PART = rf"(?:[^\W\d_]|[{_SIGN}])"
_FRAGMENT = re.compile(rf"{_PART}+")
#: What makes a reading of its own likely: a sign before letters, a letter three times in a row.
_STRONG = re.compile(rf"[^\W\d_][{_SIGN}]+[^\W\d_]|[{_SIGN}][^\W\d_]{{2}}|([^\W\d_])\1\1")
_DOUBLE = re.compile(r"([^\W\d_])\1")
_TAIL = re.compile(rf"[{_SIGN}]+$")
_RUN = re.compile(r"(.)\1*", re.DOTALL)
_ODD_RUN = re.compile(rf"([^\W\d_])\1+|([{_SIGN}])\2*")
#: Fragments of at most three characters, apart by at most three separators of any kind.
_SHORT = rf"{_PART}{{1,3}}(?!{_PART})"
_GAP = rf"(?:(?![{_SIGN}])[\W_]){{1,3}}"
_SHORTS = re.compile(rf"(?<![^\W_])(?<![{_SIGN}]){_SHORT}(?:{_GAP}{_SHORT})+")
#: The same two for texts without underscores and without decimal digits beyond ASCII, where one class holds all parts.
_FOREIGN = frozenset(c for c in map(chr, range(128, 0x110000)) if c.isdecimal())
_RUNS = rf"[\w{_SIGN}]"
_PLAIN_FRAGMENT = re.compile(rf"{_RUNS}+")
#: Possessive: no shorter stretch of one kind could be followed by the other.
_PLAIN_SHORTS = re.compile(rf"(?<!{_RUNS}){_RUNS}{{1,3}}+[^\w{_SIGN}]{{1,3}}+{_RUNS}{{1,3}}+(?!{_RUNS})(?:[^\w{_SIGN}]{{1,3}}+{_RUNS}{{1,3}}+(?!{_RUNS}))*+")
#: What parts words, and parts fragments of plain texts.
_BREAK = re.compile(r"[\W\d_]")
_PLAIN_BREAK = re.compile(rf"[^\w{_SIGN}]")
#: Different breaks in a text up to which each is replaced at once; a text with more is searched by character.
BREAKS = 64
#: Longest token or run whose reading is remembered, so that a number of entries is a number of bytes.
REMEMBERED = 64
#: Fragments that one word may be written in.
SPLIT = 24


def word_bytes(word: str) -> bytes:
    return word.encode("utf-8", "surrogatepass")


def word_key(spelled: bytes) -> int:
    """The 64 bits that a word is known by: the first half of its digest, as a signed number."""
    return int.from_bytes(md5(spelled).digest()[:8], "big", signed=True)


def pieces(text: str, whole: re.Pattern, breaks: re.Pattern) -> set[str]:
    """Distinct matches of ``whole``, which is one or more characters outside ``breaks``; white space is among the breaks.

    Only the distinct characters are classed, so the cost a character is that of a replacement and a split.
    """
    found = breaks.findall("".join(set(text)))
    if len(found) > BREAKS:
        return set(whole.findall(text))
    for c in found:
        text = text.replace(c, " ")
    return set(text.split())


class Lexicon:
    """Log probabilities of known words: sorted keys and one number each, behind a table of short hashes, since most words
    that are asked for are not known. About 20 to 28 bytes a word."""

    def __init__(self, keys: np.ndarray, short: np.ndarray, logs: np.ndarray) -> None:
        order = np.argsort(keys)
        self.keys, self.logs = keys[order].astype("int64"), logs[order].astype("float32")
        self.mask = (1 << max(8, (8 * len(keys)).bit_length())) - 1
        seen = np.zeros(self.mask + 1, "uint8")
        seen[short.astype("int64") & self.mask] = 1
        self.seen = seen.tobytes()

    def __len__(self) -> int:
        return len(self.keys)

    def get(self, word: str, default: float = -math.inf) -> float:
        spelled = word_bytes(word)
        if not self.seen[crc32(spelled) & self.mask]:
            return default
        key = word_key(spelled)
        i = int(self.keys.searchsorted(key))
        return float(self.logs[i]) if i < len(self.keys) and self.keys[i] == key else default


def grams_of(word: str) -> Iterator[str]:
    """Character n-grams of a word with its limits, up to ``ORDER``, each ending in a character of the word or its end."""
    padded = "^" * (ORDER - 1) + word + "$"
    for i in range(ORDER - 1, len(padded)):
        for k in range(1, ORDER + 1):
            yield padded[i - k + 1 : i + 1]


@dataclass
class LanguageModel:
    """Interpolated character n-grams with word limits, and known words."""

    grams: dict[str, float] = field(default_factory=dict)
    words: Lexicon = field(default_factory=lambda: Lexicon(np.empty(0, "int64"), np.empty(0, "int64"), np.empty(0)))
    floor: float = math.log(1e-4)

    @classmethod
    def fit(cls, words: DataFrame) -> LanguageModel:
        """From ``word, n`` of the whole corpus. Words that stand in two texts are known; n-grams are those of all words.

        Both are summed by Spark. What comes to the driver are the distinct n-grams, bounded by the alphabet, and 24 bytes
        for every known word.
        """

        def spelled(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            counts = Counter()
            for b in batches:
                for word, n in zip(b["word"], b["n"].tolist(), strict=True):
                    for g in grams_of(word):
                        counts[g] += n
                if len(counts) > HELD:
                    yield pd.DataFrame(list(counts.items()), columns=["gram", "n"])
                    counts.clear()
            yield pd.DataFrame(list(counts.items()), columns=["gram", "n"])

        found = words.mapInPandas(spelled, "gram string, n long").groupBy("gram").agg(F.sum("n").alias("n")).toPandas()
        counts = dict(zip(found["gram"], found["n"].tolist(), strict=True))
        before: Counter = Counter()
        for g, n in counts.items():
            before[g[:-1]] += n
        grams = {g: math.log(n / before[g[:-1]]) for g, n in counts.items()}
        every = words.agg(F.sum("n")).first()[0] or 1

        def keyed(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for b in batches:
                spelled = [word_bytes(w) for w in b["word"]]
                yield pd.DataFrame({"key": [word_key(w) for w in spelled], "short": [crc32(w) for w in spelled], "n": b["n"]}).astype("int64")

        # as Arrow: row by row the driver would hold many times these bytes
        known = words.where("n > 1").mapInPandas(keyed, "key long, short long, n long").toArrow()
        key, short, n = (known[c].to_numpy() for c in ("key", "short", "n"))
        return cls(grams, Lexicon(key, short, np.log(n / every)))

    def step(self, history: str, char: str) -> float:
        """Log probability of a character after the last ones, backing off to shorter histories."""
        p = self.grams.get(history + char)
        if p is not None:
            return p
        for k in range(1, len(history) + 1):
            p = self.grams.get(history[k:] + char)
            if p is not None:
                return p + _BACK * k
        return self.floor + _BACK * len(history)


@lru_cache(maxsize=10_000)
def run_readings(char: str, n: int) -> list[tuple[str, float]]:
    letters = [(char, 0.0)] if char.isalpha() else [(c, COST["sign"]) for c in SIGNS.get(char, "")]
    return [(c * k, cost + COST["repeat"] * (n > k)) for c, cost in letters for k in sorted({1, min(2, n), n})] or [("", COST["gap"])]


def lattice(token: str) -> list[list[tuple[str, float]]]:
    """Per run of equal characters its readings, each with a cost: once, twice, or as written. Letters that stand alone
    have one reading and go together."""
    out, at = [], 0
    for m in _ODD_RUN.finditer(token):
        if m.start() > at:
            out += plain_steps(token[at : m.start()])
        out.append(run_readings(token[m.start()], m.end() - m.start()))
        at = m.end()
    return out + plain_steps(token[at:]) if at < len(token) else out


def plain_steps(letters: str) -> list[list[tuple[str, float]]]:
    return [[(letters, 0.0)]] if letters.isalpha() else [run_readings(c, 1) for c in letters]


def word_score(text: str, spelled: float, model: LanguageModel) -> float:
    """Log probability of a whole word: spelled by characters, its end included, or known."""
    return max(math.log(1 - WORD_SHARE) + spelled, math.log(WORD_SHARE) + model.words.get(text))


def search(steps: list[list[tuple[str, float]]], model: LanguageModel) -> tuple[float, str]:
    """Score and text of the most likely word of a lattice: Viterbi over the last characters, then known words against
    the spelled ones."""
    # a reading is a chain of pieces, so that long tokens cost no more a character than short ones
    states: dict[str, list[tuple]] = {"^" * (ORDER - 1): [(0.0, 0.0, None)]}
    step = model.step
    for readings in steps:
        after: dict[str, list[tuple]] = {}
        for history, best in states.items():
            for letters, cost in readings:
                h, p = history, cost
                for c in letters:
                    p += step(h, c)
                    h = (h + c)[-(ORDER - 1) :]
                after.setdefault(h, []).extend([(s + p, paid + cost, (chain, letters)) for s, paid, chain in best])
        # a few readings per state are kept, so that a known word is not lost to a better-spelled neighbour
        states = {h: sorted(v, key=itemgetter(0), reverse=True)[:4] if len(v) > 1 else v for h, v in after.items()}
        if len(states) > BEAM:
            states = dict(sorted(states.items(), key=lambda x: -x[1][0][0])[:BEAM])
    ends = []
    for h, best in states.items():
        for s, paid, chain in best:
            pieces = []
            while chain:
                chain, letters = chain
                pieces.append(letters)
            if text := "".join(reversed(pieces)):
                ends.append((paid + word_score(text, s - paid + step(h, "$"), model), text))
    return max(ends, default=(-math.inf, ""))


def known_readings(steps: list[list[tuple[str, float]]], model: LanguageModel, most: int = 64) -> tuple[float, str]:
    """The most likely known word among the readings of a lattice; a lattice with very many is searched."""
    if math.prod(map(len, steps)) > most:
        score, text = search(steps, model)
        return (score, text) if text and model.words.get(text) > -math.inf else (-math.inf, "")
    best = (-math.inf, "")
    for path in product(*steps):
        text = "".join([letters for letters, _ in path])
        p = model.words.get(text)
        if p > -math.inf:
            best = max(best, (math.log(WORD_SHARE) + p + sum([cost for _, cost in path]), text))
    return best


def decode(token: str, model: LanguageModel) -> str:
    """Most likely reading of a token; signs at its end are read as letters or left."""
    tail = _TAIL.search(token)
    ends = [len(token)] + ([tail.start() + m.start() for m in _RUN.finditer(tail.group())] if tail else [])
    read, plain = [], []
    for end in ends:
        # signs from ``end`` on stay as they are
        core = token[:end]
        if not _WORD.search(core):
            continue
        score, text = (search if _STRONG.search(core) else known_readings)(lattice(core), model)
        kept = COST["literal"] * sum(1 for _ in groupby(token[end:]))
        if text and text != core:
            read.append((score + kept, text + token[end:]))
        elif core.isalpha():
            plain.append((core, kept))
    if not read:
        return token
    # against the token as written
    return max(read + [(search([[(c, 0.0)] for c in core], model)[0] + kept, token) for core, kept in plain])[1]


class Restorer:
    """Restored words of a text; readings of short tokens are remembered, up to a bound."""

    def __init__(self, model: LanguageModel, remember: int = 300_000) -> None:
        self.model, self.remember = model, remember
        self.known: dict[str, str] = {}
        self.runs: dict[str, str] = {}
        self.logs: dict[str, float] = {}
        self.scored: dict[str, tuple[float, str]] = {}
        #: Letters only, read as they are; runs without a gap to close.
        self.plain: set[str] = set()
        self.still: set[str] = set()

    def keep(self, memory: dict | set, key: str) -> bool:
        """Whether ``key`` may be remembered; a full memory is emptied first."""
        if len(memory) >= self.remember:
            memory.clear()
        return len(key) <= REMEMBERED

    def log(self, word: str) -> float:
        p = self.logs.get(word)
        if p is None:
            p = self.model.words.get(word)
            if self.keep(self.logs, word):
                self.logs[word] = p
        return p

    def read(self, token: str) -> str:
        word = self.known.get(token)
        if word is None:
            if not _WORD.search(token) or (token.isalpha() and not _DOUBLE.search(token)):
                return token
            word = decode(token, self.model)
            if self.keep(self.known, token):
                self.known[token] = word
        return word

    def close(self, run: str) -> str:
        """A run of short fragments with the gaps closed that make its words more likely."""
        text = self.runs.get(run)
        if text is None:
            text = self._close(run)
            if self.keep(self.runs, run):
                self.runs[run] = text
        return text

    def _close(self, run: str) -> str:
        found = list(_FRAGMENT.finditer(run))
        parts = [m.group() for m in found]
        gaps = [run[x.end() : y.start()] for x, y in zip(found, found[1:], strict=False)] + [""]
        out, i = [], 0
        for start, end in self._stretches(parts):
            out += [parts[k] + gaps[k] for k in range(i, start)]
            out.append(self._words(parts[start:end], gaps[start:end]))
            i = end
        return "".join(out + [parts[k] + gaps[k] for k in range(i, len(parts))])

    def _stretches(self, parts: list[str]) -> list[tuple[int, int]]:
        """Where gaps may be closed: by single characters with what stands next to them, and where fragments together are a
        known word that is more frequent than each of them."""
        log, seen, n = self.log, self.logs.get, len(parts)
        logs = [log(x) if (p := seen(x)) is None else p for x in parts]
        spans = [(max(i - 1, 0), min(i + 3, n)) for i in range(n - 1) if len(parts[i]) == len(parts[i + 1]) == 1 and (parts[i] + parts[i + 1]).strip(_SIGNS)]
        for i in range(n - 1):
            text, top = parts[i], logs[i]
            for j in range(i + 1, min(i + 6, n)):
                text += parts[j]
                if logs[j] > top:
                    top = logs[j]
                if text.isalpha() and (log(text) if (p := seen(text)) is None else p) > top:
                    spans.append((i, j + 1))
        out: list[tuple[int, int]] = []
        for a, b in sorted(spans):
            if out and a < out[-1][1]:
                out[-1] = (out[-1][0], max(b, out[-1][1]))
            else:
                out.append((a, b))
        return out

    def _words(self, parts: list[str], gaps: list[str]) -> str:
        """Most likely words of fragments: every gap closes at its cost or ends a word. A fragment of more than a character
        stays a word where it is more frequent than what it would be part of."""
        steps = [lattice(x) for x in parts]
        logs = [self.log(x) if len(x) > 1 else -math.inf for x in parts]
        best: list[tuple[float, int, str]] = [(0.0, 0, "")]
        for j in range(1, len(parts) + 1):
            ways = []
            for i in range(max(0, j - SPLIT), j):
                if any(_WORD.search(x) for x in parts[i:j]):
                    score, text = self.joined(parts[i:j], steps[i:j])
                    top = max(logs[i:j])
                    if j - i == 1 or top == -math.inf or top < self.log(text):
                        ways.append((best[i][0] + score + COST["gap"] * (j - i - 1), i, text))
                elif i == j - 1:
                    ways.append((best[i][0] + COST["literal"] * len(steps[i]), i, parts[i]))
            best.append(max(ways))
        out, j = [], len(parts)
        while j:
            _, i, text = best[j]
            out.append((parts[i] if i == j - 1 else text) + gaps[j - 1])
            j = i
        return "".join(reversed(out))

    def joined(self, parts: list[str], steps: list) -> tuple[float, str]:
        key = " ".join(parts)
        found = self.scored.get(key)
        if found is None:
            found = search([x for s in steps for x in s], self.model)
            if self.keep(self.scored, key):
                self.scored[key] = found
        return found

    def words(self, text: str | None) -> set[str]:
        """Distinct words in lower case, as written and as restored."""
        text = (text or "").lower()
        if not (text.isascii() or _FOREIGN.isdisjoint(set(text))):
            found, shorts = set(_FRAGMENT.findall(text)), _SHORTS
        else:
            text, shorts = text.replace("_", " "), _PLAIN_SHORTS
            found = pieces(text, _PLAIN_FRAGMENT, _PLAIN_BREAK)
        for token in found - self.plain:
            word = self.read(token)
            if token.isalpha():
                if word != token:
                    found.update(_WORD.findall(word))
                elif self.keep(self.plain, token):
                    self.plain.add(token)
            else:
                found.discard(token)
                found.update(_WORD.findall(token))
                if word != token:
                    found.update(_WORD.findall(word))
        for run in set(shorts.findall(text)) - self.still:
            closed = self.close(run)
            if closed != run:
                found.update(_WORD.findall(closed))
            elif self.keep(self.still, run):
                self.still.add(run)
        return found

    def restored(self, text: str | None) -> str:
        """The text in lower case with every odd token replaced by its reading."""
        text = _SHORTS.sub(lambda m: self.close(m.group()), (text or "").lower())
        return _FRAGMENT.sub(lambda m: self.read(m.group()), text)


def features(word: str) -> list[str]:
    """A word is evidence itself, and so are its beginnings (marked, so they never equal a word)."""
    return [word, *[f"{word[:k]}*" for k in STEMS if len(word) > k]]


@dataclass
class ToxicityModel:
    language: LanguageModel
    weights: dict[str, float]
    bias: float
    slope: float

    def weight(self, word: str) -> float:
        """The strongest weight among a word and its beginnings."""
        get = self.weights.get
        return max([get(f, 0.0) for f in features(word)])

    def evidence(self, words: Iterable[str]) -> float:
        return math.fsum(map(self.weight, words))

    def curve(self, evidence: float) -> float:
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, self.bias + self.slope * evidence))))

    def score(self, words: Iterable[str]) -> float:
        return self.curve(self.evidence(words))

    @cached_property
    def scorer(self) -> Scorer:
        """One a Python worker, so that its tasks share what it remembers; not part of what is sent to them."""
        return Scorer(self)


class Scorer:
    """Scores of whole texts under a model; words without evidence are remembered, up to a bound."""

    def __init__(self, model: ToxicityModel) -> None:
        self.model, self.restorer, self.idle = model, Restorer(model.language), set()
        #: A word without one of these beginnings has no evidence: a feature is a word or at least its first four letters.
        self.heads = {f.removesuffix("*")[: STEMS[0]] for f in model.weights}

    def evidence(self, text: str | None) -> float:
        found, weight, heads, k = [], self.model.weight, self.heads, STEMS[0]
        for word in self.restorer.words(text) - self.idle:
            if word[:k] in heads and (w := weight(word)):
                found.append(w)
            elif self.restorer.keep(self.idle, word):
                self.idle.add(word)
        return math.fsum(found)

    def score(self, text: str | None) -> float:
        return self.model.curve(self.evidence(text))


def held_out(id_col: str) -> Column:
    """Rows whose labels are never learnt from."""
    return F.coalesce(F.crc32(F.encode(F.col(id_col).cast("string"), "UTF-8")) % 4 == 2, F.lit(False))


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", sample: int = SAMPLE) -> ToxicityModel:
    """The language model from all of ``docs``; evidence from at most ``sample`` labelled rows that are not held out.

    One pass counts both, with partial counts per task. What comes to the driver for the evidence is bounded by the sample:
    its identifiers, and the features of its texts with two counts each. Labels of held-out rows are never read.
    """
    chosen = labels.where(F.col(id_col).isNotNull() & F.col(label_col).isNotNull() & ~held_out(id_col)).groupBy(F.col(id_col).cast("long").alias("i")).agg(F.max(F.col(label_col)).cast("int").alias("y"))
    chosen = stored(chosen.orderBy(F.xxhash64("i"), "i").limit(sample), "chosen")
    every = docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("text")).join(F.broadcast(chosen), "i", "left")  # chosen: at most ``sample`` rows

    def words(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        plain, seen, toxic, n = Counter(), Counter(), Counter(), [0, 0]

        def rows() -> pd.DataFrame:
            found = [*plain, *seen, ""]
            counts = np.fromiter(chain(plain.values(), seen.values(), [n[0] + n[1]]), "int64", len(found))
            hits = np.fromiter(chain(repeat(0, len(plain)), map(toxic.__getitem__, seen), [n[1]]), "int64", len(found))
            out = pd.DataFrame({"feature": found, "n": counts, "toxic": hits, "plain": np.arange(len(found)) < len(plain)})
            for c in (plain, seen, toxic):
                c.clear()
            n[:] = 0, 0
            return out

        for b in batches:
            for text, y in zip(b["text"], b["y"].tolist(), strict=True):
                found = pieces((text or "").lower(), _WORD, _BREAK)
                plain.update(found)
                if y == y and y is not None:
                    found = {f for w in found if len(w) <= 64 for f in features(w)}
                    seen.update(found)
                    n[y > 0] += 1
                    if y > 0:
                        toxic.update(found)
            if len(plain) + len(seen) > HELD:
                yield rows()
        yield rows()

    counted = every.mapInPandas(words, "feature string, n long, toxic long, plain boolean").groupBy("plain", "feature").agg(*[F.sum(c).alias(c) for c in ("n", "toxic")])
    counted = stored(counted, "words")
    counts = counted.where("not plain and (toxic > 2 or feature = '')").toPandas()
    total = counts[counts["feature"] == ""][["n", "toxic"]].sum()
    language = LanguageModel.fit(counted.where("plain").select(F.col("feature").alias("word"), "n"))
    weights = _weights(counts[counts["feature"] != ""], int(total["n"]), int(total["toxic"]))
    model = ToxicityModel(language, weights, 0.0, 1.0)
    texts = every.where("y is not null")

    def evidence(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        scorer = Scorer(model)
        for b in batches:
            yield pd.DataFrame({"x": [scorer.evidence(x) for x in b["text"]], "y": b["y"]})

    known = texts.mapInPandas(evidence, "x double, y int").toPandas()  # at most ``sample`` rows
    model.bias, model.slope = _calibrate(known["x"].to_numpy(), known["y"].to_numpy())
    return model


def _weights(counts: pd.DataFrame, n: int, toxic: int) -> dict[str, float]:
    """Log odds ratios of the features that stand in more toxic texts than chance allows, given how many are tried."""
    weights, share = {}, max(toxic, 1) / max(n, 1)
    if share >= 1:
        return weights
    clear = 2 * math.log(max(len(counts), 2))
    for f, k, t in zip(counts["feature"], counts["n"].tolist(), counts["toxic"].tolist(), strict=True):
        rest = k - t
        ratio = math.log((t + 0.5) / (toxic + 1)) - math.log((rest + 0.5) / (n - toxic + 1))
        # likelihood ratio of the counts against the base rate
        g = 2 * (t * math.log(t / (k * share)) + (rest * math.log(rest / (k * (1 - share))) if rest else 0))
        if ratio > 1.5 and g > clear:
            weights[f] = ratio
    return dict(sorted(weights.items(), key=lambda x: -x[1])[:FEATURES])


def _calibrate(x: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Bias and slope of a logistic curve with a weak prior, by Newton steps; a constant when one label is missing."""
    if len(y) == 0 or y.min() == y.max():
        rate = (y.sum() + 0.5) / (len(y) + 10)
        return math.log(rate / (1 - rate)), 0.0 if len(y) == 0 else 1.0
    x = x.astype(float)
    w = np.array([math.log(max(y.mean(), 1e-6) / max(1 - y.mean(), 1e-6)), 0.1])
    design = np.column_stack([np.ones_like(x), x])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(design @ w, -30, 30)))
        gradient = design.T @ (y - p) - 1e-2 * w
        hessian = (design * (p * (1 - p))[:, None]).T @ design + 1e-2 * np.eye(2)
        step = np.linalg.solve(hessian, gradient)
        w = w + np.clip(step, -2, 2)
        if np.abs(step).max() < 1e-8:
            break
    return float(w[0]), float(max(w[1], 1e-3))


def score(docs: DataFrame, model: ToxicityModel, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.3, with_restored: bool = False) -> DataFrame:
    """``doc_id, held_out, score, predicted`` for every whole text, and on request ``restored``.

    A null text is empty and gets the score of a text without evidence; null identifiers are never held out; repeated rows
    get equal scores; other columns are not read; an empty table gives an empty result. One pass, no shuffle; the model is
    broadcast: evidence is bounded by ``FEATURES``, n-grams by the alphabet, and a known word of the corpus takes 20 to 28 bytes.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)
    schema = "doc_id bigint, held_out boolean, score double, predicted int" + (", restored string" if with_restored else "")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        scorer = shared.value.scorer
        for b in batches:
            s = np.array([scorer.score(t) for t in b["text"]], dtype=float)
            out = pd.DataFrame({"doc_id": b["doc_id"].astype("Int64"), "held_out": b["held_out"], "score": s, "predicted": (s >= threshold).astype("int32")})
            if with_restored:
                out["restored"] = [scorer.restorer.restored(t) for t in b["text"]]
            yield out

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), held_out(id_col).alias("held_out"), F.col(text_col).alias("text")).mapInPandas(run, schema)


def scorer(spark: SparkSession, model: ToxicityModel):
    """A column function from text to score, for filters that must not move texts."""
    shared = spark.sparkContext.broadcast(model)

    @F.pandas_udf("double")
    def toxic(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        scorer = shared.value.scorer
        for texts in parts:
            yield pd.Series([scorer.score(t) for t in texts], dtype="float64")

    return toxic
