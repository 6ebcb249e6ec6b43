"""Secret scans: fixed formats, and formats inferred as probabilistic automata.

Labelled credentials are gathered in a prefix tree with counts.  States whose
outgoing frequencies agree within a Hoeffding bound (recursively) are merged,
which turns the tree into a small probabilistic automaton.  Labels come from two
sources: credentials drawn by a seeded generator from published formats, and
the values of base spans of the whole corpus.  Of the corpus only tables of fixed
size reach the driver: the prefix tree's nodes that are frequent enough to be told
apart, what follows below them pooled by pairs of neighbouring classes, the pairs of
ordinary tokens, and a histogram of the gains of those that were held out.

Two kinds of automata are inferred.  *Format automata* read a format's first
``literal`` places literally and character classes after that; they name known
formats wherever in a run of token characters their start occurs.  The *general
automaton* reads classes only and is inferred from all labelled credentials
together, so it accepts formats that no list knows.  Every run of token
characters of every text is its candidate, whatever its start or length: along a
run the gain of each sign is its log likelihood in the automaton less that in a
background of ordinary tokens, and segments between separators whose summed gain
passes the threshold become spans.  The threshold lies a margin above the best
segments of ordinary tokens that were held out.  A run is walked only if an upper
bound of its gains (from pairs of neighbouring classes, summed for whole batches
at once) reaches the threshold; what the bound excludes could not pass.
"""

from __future__ import annotations

import bisect
import hashlib
import math
import re
from collections import Counter
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .textbatch import LOWER, Words, byte_class, slices
from .workspace import Workspace

ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.A | re.I)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]+")
KINDS = ("assign", "access", "hex")
_CUES = (b"password", b"passwd", b"secret", b"token", b"api_key", b"apikey")
_TOKEN = re.compile(r"[A-Za-z0-9+/_.=-]+")
#: What every text with a base span holds.
_HINT = re.compile(r"AKIA|[0-9a-f]{24}|password|passwd|secret|token|api_?key", re.A | re.I)
_TOKEN_ALPHABET = "+/_.=-"
#: Signs after which a credential may begin and before which it may end.
_SEPARATORS = "=/+."
#: Fixed value: universally unique identifiers, which name things and open nothing.
_UUID = re.compile(r"[0-9A-Fa-f]{8}-(?:[0-9A-Fa-f]{4}-){3}[0-9A-Fa-f]{12}")
#: Three dotted segments: header, payload, signature.
_JWT = re.compile(r"eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+")
_HEX_BYTES = byte_class(lambda b: 0x30 <= b <= 0x39 or 0x61 <= b <= 0x66)

_BASE62 = "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"
#: Published credential formats as (kind, prefix, alphabet, lengths of the rest).
FORMATS = (
    ("github", "ghp_", _BASE62, (36, 36)),
    ("github", "gho_", _BASE62, (36, 36)),
    ("gitlab", "glpat-", _BASE62 + "_-", (20, 20)),
    ("slack", "xoxb-", "0123456789-" + _BASE62, (45, 60)),
    ("stripe", "sk_live_", _BASE62, (24, 32)),
    ("google", "AIza", _BASE62 + "_-", (35, 35)),
    ("npm", "npm_", _BASE62, (36, 36)),
    ("jwt", "eyJ", _BASE62 + "_-", (17, 60)),
)
#: Lengths of a dotted JWT's header after its prefix, payload and signature.
JWT_PARTS = ((14, 60), (3, 160), (43, 86))
_EXTENTS = {prefix: re.compile(re.escape(prefix) + f"[{re.escape(alphabet)}]*") for _, prefix, alphabet, _ in FORMATS}
_STARTS = (b"AKIA", *(prefix.encode() for _, prefix, _, _ in FORMATS))
_PREFIX = re.compile("|".join(re.escape(prefix) for _, prefix, _, _ in FORMATS))


@dataclass(frozen=True)
class AutomatonSettings:
    """examples: labelled credentials per format; alpha: confidence parameter of the merge test;
    literal: places read literally; threshold: bits per character over the background that a known
    format needs; labelled: weight, in examples, of all the corpus's values of base spans together where
    they are more; depth: places of the prefix tree (later ones are pooled); ordinary: generated
    ordinary tokens; margin: bits that the general automaton's
    threshold lies above held-out ordinary tokens; trusted: share of the corpus's tokens that are
    taken for ordinary; miss: bits lost where it has no transition; seed."""

    examples: int = 160
    alpha: float = 0.05
    literal: int = 4
    threshold: float = 0.25
    labelled: int = 200
    depth: int = 200
    ordinary: int = 6000
    margin: float = 4.0
    trusted: float = 0.97
    miss: float = 8.0
    seed: int = 3


def symbols(text: str, literal: int) -> list[str]:
    """Literal characters first, then classes: digit, upper, lower, or the sign itself."""
    out = list(text[:literal])
    for c in text[literal:]:
        out.append("0" if c.isdigit() else "A" if c.isupper() else "a" if c.islower() else c)
    return out


@dataclass
class _State:
    ends: int = 0
    passed: int = 0
    next: dict = field(default_factory=dict)


@dataclass(frozen=True)
class Corpus:
    """What training takes from the corpus, counted over all of it, in tables of fixed size.

    nodes: (passed, ended) of the kept prefixes of labelled values, one letter a class; exits:
    steps from a kept prefix (and a class) to one that is not kept; tail: steps after that, by two
    neighbouring classes (-1: the end); pairs: neighbouring classes of ordinary tokens; gains:
    (bin, tokens) of the best segments of the ordinary tokens held out.
    """

    nodes: dict[str, tuple[float, float]] = field(default_factory=dict)
    exits: dict[tuple[str, int], float] = field(default_factory=dict)
    tail: dict[tuple[int, int], float] = field(default_factory=dict)
    pairs: np.ndarray | None = None
    gains: tuple[tuple[int, int], ...] = ()


class Automaton:
    """A probabilistic automaton; state 0 is the start."""

    def __init__(self, samples: list[list[str]], alpha: float, corpus: Corpus | None = None):
        self.states = [_State()]
        self.pooled: dict[int, int] = {}
        for sample in samples:
            at = 0
            self.states[0].passed += 1
            for s in sample:
                if s not in self.states[at].next:
                    self.states[at].next[s] = [len(self.states), 0]
                    self.states.append(_State())
                edge = self.states[at].next[s]
                edge[1] += 1
                at = edge[0]
                self.states[at].passed += 1
            self.states[at].ends += 1
        if corpus:
            self._graft(corpus)
        self.bound = merge_bound(alpha)
        self._merge_all()

    def _graft(self, corpus: Corpus) -> None:
        """Adds the corpus's tree; its pooled tails are states of their own, one a class."""
        for c in {c for _, c in corpus.exits}.union(*corpus.tail) - {-1}:
            self.pooled[c] = len(self.states)
            self.states.append(_State())
        where = {"": 0}
        for prefix, (passed, ends) in sorted(corpus.nodes.items(), key=lambda x: (len(x[0]), x[0])):
            if prefix:
                following = self.states[where[prefix[:-1]]].next
                edge = following.get(_class_at(prefix[-1]))
                if edge is None:
                    edge = following[_class_at(prefix[-1])] = [len(self.states), 0]
                    self.states.append(_State())
                edge[1] += passed
                where[prefix] = edge[0]
            self.states[where[prefix]].passed += passed
            self.states[where[prefix]].ends += ends
        for (prefix, c), n in sorted(corpus.exits.items()):
            self.states[where[prefix]].next.setdefault(c, [self.pooled[c], 0])[1] += n
        for (c, d), n in sorted(corpus.tail.items()):
            state = self.states[self.pooled[c]]
            state.passed += n
            if d < 0:
                state.ends += n
            else:
                state.next.setdefault(d, [self.pooled[d], 0])[1] += n

    def _differ(self, a: int, n: int, b: int, m: int) -> bool:
        return abs(a / n - b / m) > self.bound * (1 / math.sqrt(n) + 1 / math.sqrt(m))

    def _compatible(self, red: int, blue: int) -> bool:
        todo = [(red, blue)]
        met = set(todo)
        while todo:
            i, j = todo.pop()
            p, q = self.states[i], self.states[j]
            if min(p.passed, q.passed) <= self.bound**2:  # too few to differ, and those below are fewer
                continue
            if self._differ(p.ends, p.passed, q.ends, q.passed):
                return False
            for s in p.next.keys() | q.next.keys():
                e, f = p.next.get(s), q.next.get(s)
                if self._differ(e[1] if e else 0, p.passed, f[1] if f else 0, q.passed):
                    return False
                if e and f and e[0] != f[0] and (e[0], f[0]) not in met:  # pooled states may lead back
                    met.add((e[0], f[0]))
                    todo.append((e[0], f[0]))
        return True

    def _fold(self, red: int, blue: int) -> None:
        todo = [(red, blue)]
        pooled = set(self.pooled.values())
        while todo:
            i, j = todo.pop()
            p, q = self.states[i], self.states[j]
            p.ends += q.ends
            p.passed += q.passed
            for s, (to, n) in q.next.items():
                if s in p.next:
                    p.next[s][1] += n
                    if p.next[s][0] != to and to not in pooled:  # those keep their own counts
                        todo.append((p.next[s][0], to))
                else:
                    p.next[s] = [to, n]

    def _merge_all(self) -> None:
        red = [0, *self.pooled.values()]
        while True:
            marked = set(red)
            blue = [(r, s) for r in red for s in sorted(self.states[r].next) if self.states[r].next[s][0] not in marked]
            if not blue:
                break
            r, s = max(blue, key=lambda e: self.states[self.states[e[0]].next[e[1]][0]].passed)
            b = self.states[r].next[s][0]
            for candidate in red:
                if self._compatible(candidate, b):
                    self.states[r].next[s][0] = candidate
                    self._fold(candidate, b)
                    break
            else:
                red.append(b)
        self.size = len(red)

    def log_probability(self, sample: list[str]) -> float:
        """Base-2 log of the probability of exactly this string; -inf if impossible."""
        at, total = 0, 0.0
        for s in sample:
            state = self.states[at]
            edge = state.next.get(s)
            if edge is None:
                return -math.inf
            total += math.log2(edge[1] / state.passed)
            at = edge[0]
        state = self.states[at]
        return total + math.log2(state.ends / state.passed) if state.ends else -math.inf


def merge_bound(alpha: float) -> float:
    """Factor of the Hoeffding bound; states passed by no more than its square cannot be told apart."""
    return math.sqrt(0.5 * math.log(2 / alpha))


def _class_of(byte: int) -> int:
    """Digit 0, upper 1, lower 2, the signs of ``_TOKEN_ALPHABET`` from 3 on, anything else -1."""
    c = chr(byte)
    if byte < 128 and c.isalnum():
        return 0 if c.isdigit() else 1 if c.isupper() else 2
    return 3 + _TOKEN_ALPHABET.index(c) if byte < 128 and c in _TOKEN_ALPHABET else -1


_CLASSES = np.array([_class_of(b) for b in range(256)], np.int8)
_START = 3 + len(_TOKEN_ALPHABET)
_LETTERS = "abcdefghijklmnopqrstuvwxyz"
#: Bins of a bit, and their number, of the histogram of gains.
_BINS, _MOST_BINS = 64, 1 << 16


def _class_at(letter: str) -> int:
    return _LETTERS.index(letter)


def _classes_of(token: str) -> np.ndarray:
    return _CLASSES[np.frombuffer(token.encode(), np.uint8)].astype(np.int64)


def _pattern(token: str) -> str:
    """One letter a class."""
    return "".join(map(_LETTERS.__getitem__, _classes_of(token).tolist()))


def _pairs(tokens) -> np.ndarray:
    """Counts of neighbouring classes (the start first) in tokens."""
    counts = np.zeros((_START + 1, _START), np.int64)
    for token in tokens:
        at = np.concatenate(([_START], _classes_of(token)))
        if (at >= 0).all():
            np.add.at(counts, (at[:-1], at[1:]), 1)
    return counts


_SEPARATING = frozenset(3 + _TOKEN_ALPHABET.index(c) for c in _SEPARATORS)


def ordinary_tokens(n: int, seed: int) -> list[str]:
    """Seeded tokens of everyday text and code: words, identifiers, paths, hosts, numbers, dates, versions, codes."""
    rng = np.random.Generator(np.random.PCG64(seed))
    pick = lambda x: x[int(rng.integers(len(x)))]
    syllables = "an the re tion er in st de con ver sion al ic ment ing lo ra mi to na se per for ma ti on co un di ex pro".split()
    word = lambda: "".join(pick(syllables) for _ in range(int(rng.integers(1, 5))))
    number = lambda k: "".join(str(x) for x in rng.integers(0, 10, int(rng.integers(1, k + 1))))
    title = lambda: word().capitalize()
    date = lambda: f"{rng.integers(1990, 2035)}-{rng.integers(1, 13):02d}-{rng.integers(1, 29):02d}"
    shapes = (
        word, title, lambda: word().upper(), lambda: f"{word()}.", lambda: number(18), date,
        lambda: word() + "".join(title() for _ in range(int(rng.integers(1, 5)))),
        lambda: "".join(title() for _ in range(int(rng.integers(2, 6)))) + number(2),
        lambda: "_".join(word() for _ in range(int(rng.integers(2, 6)))),
        lambda: "_".join(word().upper() for _ in range(int(rng.integers(2, 6)))),
        lambda: "-".join(word() for _ in range(int(rng.integers(2, 9)))),
        lambda: ".".join(word() for _ in range(int(rng.integers(2, 5)))),
        lambda: "/".join(word() for _ in range(int(rng.integers(2, 8)))) + f".{word()[:4]}",
        lambda: f"www.{word()}.{pick(['com', 'org', 'net'])}/{date().replace('-', '/')}/{'-'.join(word() for _ in range(int(rng.integers(2, 7))))}.html",
        lambda: f"v{rng.integers(0, 30)}.{rng.integers(0, 30)}.{rng.integers(0, 300)}-{pick(['beta', 'rc', 'alpha'])}.{rng.integers(1, 9)}",
        lambda: f"IMG_{date().replace('-', '')}_{rng.integers(0, 10**6):06d}.jpg",
        lambda: f"{date()}T{rng.integers(0, 24):02d}-{rng.integers(0, 60):02d}-{rng.integers(0, 60):02d}.{rng.integers(0, 1000):03d}Z",
        lambda: f"{word().upper()[:3]}-{rng.integers(0, 10**5)}-{word().upper()[:2]}",
        lambda: f"{word()}={word()}", lambda: f"{word().upper()}={number(6)}", lambda: f"{word()}{number(4)}", lambda: f"{word()}_{number(4)}.{word()[:3]}",
        lambda: f"{title()}{number(3)}{title()}", lambda: f"{number(5)}.{number(5)}", lambda: f"{word()}-{number(5)}-{number(3)}/{title()}",
        lambda: f"{number(4)}-{number(4)}-{number(4)}-{number(4)}", lambda: "=" * int(rng.integers(3, 80)), lambda: "-" * int(rng.integers(3, 80)), lambda: "." * int(rng.integers(3, 20)),
        lambda: f"{pick('ABCDEFGH')}{number(2)}{pick('ABCDEFGH')}{number(3)}", lambda: f"x{number(2)}_{number(2)}-{word()}-{word()[:3]}",
    )
    return [shapes[i % len(shapes)]() for i in range(n)]


class GeneralModel:
    """The automaton of all labelled credentials, the background of ordinary tokens, and the threshold."""

    def __init__(self, credentials: list[str], settings: AutomatonSettings, corpus: Corpus = Corpus()):
        kept = [c for c in credentials if c and all(_CLASSES[b] >= 0 for b in c.encode())]
        automaton = Automaton([_CLASSES[np.frombuffer(c.encode(), np.uint8)].tolist() for c in kept], settings.alpha, corpus)
        width, miss = _START, -settings.miss
        reach, todo = {0: 0}, [0]
        while todo:
            for to, _ in automaton.states[todo.pop()].next.values():
                if to not in reach:
                    reach[to] = len(reach)
                    todo.append(to)
        self.size = len(reach)
        #: Next state and log2 probability of each state and class; where there is no transition the walk starts over.
        self.next, self.logs = np.zeros((self.size, width), np.int32), np.full((self.size, width), miss - 4.0)
        for old, new in reach.items():
            state = automaton.states[old]
            for s, (to, n) in state.next.items():
                self.next[new, s], self.logs[new, s] = reach[to], math.log2(n / state.passed)
        first_next, first_logs = self.next[0].copy(), self.logs[0].copy()
        for q in range(self.size):
            for s in range(width):
                if self.logs[q, s] <= miss - 4.0:
                    self.next[q, s] = first_next[s]
                    self.logs[q, s] = min(miss, miss + first_logs[s]) if first_logs[s] > miss - 4.0 else miss - 4.0
        made = ordinary_tokens(settings.ordinary, settings.seed)
        counts = 0.5 + _pairs(made[::2]) + (0 if corpus.pairs is None else corpus.pairs)
        self.background = np.log2(counts / counts.sum(1, keepdims=True))
        self._walk = self.next.tolist(), self.logs.tolist(), self.background.tolist()
        self.threshold = max(map(self.best, made[1::2]), default=0.0) + settings.margin
        # Some of the corpus's own tokens may be credentials that no base span labels, so its best ones set no bar.
        rank = int(settings.trusted * (sum(n for _, n in corpus.gains) - 1))
        for at, n in sorted(corpus.gains):
            if rank < n:
                self.threshold = max(self.threshold, at / _BINS + settings.margin)
                break
            rank -= n
        # The most that a class can gain after another one, over all states that the walk may be in.
        entered = {s: {0} if s in _SEPARATING or s == _START else set() for s in range(width + 1)}
        for q in range(self.size):
            for s in range(width):
                entered[s].add(int(self.next[q, s]))
        self.most = np.array([[max((self.logs[q, t] for q in entered[s]), default=-np.inf) - self.background[s, t] for t in range(width)] for s in range(width + 1)])

    def best(self, token: str) -> float:
        """The largest gain of a segment of a token."""
        return max((gain for _, _, gain in self.segments(token, 0.0)), default=0.0)

    def segments(self, run: str, threshold: float | None = None) -> list[tuple[int, int, float]]:
        """(start, end, gain) of the best segments of a run of token characters, left to right.

        A segment starts at the run's start or after a separator and ends before
        one or at the run's end; a walk whose gain is used up starts over at the
        next separator.
        """
        least = self.threshold if threshold is None else threshold
        following, logs, background = self._walk
        classes = _CLASSES[np.frombuffer(run.encode(), np.uint8)].tolist()
        out: list[tuple[int, int, float]] = []
        n = len(classes)
        start, state, gain, before = 0, 0, 0.0, _START
        best, best_end = -1.0, -1
        for i in range(n + 1):
            if i == n or classes[i] in _SEPARATING:
                if gain > best and i > start:
                    best, best_end = gain, i
                over = i == n or gain <= 0 or gain < best - 20.0
                if over and best >= least and best > 0:
                    out.append((start, best_end, best))
                if over:
                    start, state, gain, before = i + 1, 0, 0.0, _START
                    best, best_end = -1.0, -1
                    continue
            s = classes[i]
            gain += logs[state][s] - background[before][s]
            state, before = following[state][s], s
        return out

    def may_pass(self, raw: np.ndarray, borders: np.ndarray) -> np.ndarray:
        """Rows that hold a run whose gains could reach the threshold."""
        classes = _CLASSES[raw].astype(np.int64)
        inside = classes >= 0
        if not inside.any():
            return np.empty(0, np.int64)
        first = inside.copy()
        first[1:] &= ~inside[:-1]
        heads = borders[:-1][borders[:-1] < borders[1:]]
        first[heads] = inside[heads]
        before = np.empty_like(classes)
        before[1:] = classes[:-1]
        before[first] = _START
        spot = np.flatnonzero(inside)
        gains = np.maximum(self.most, 0.0)[before[spot], classes[spot]]
        starts = np.flatnonzero(first[spot])
        best = np.add.reduceat(gains, starts)
        return np.unique(np.searchsorted(borders, spot[starts[best >= self.threshold]], "right") - 1)


class FormatModel:
    """One automaton per format kind and literal start, the general automaton, and the background.

    ``corpus`` holds what is counted in the corpus.
    """

    def __init__(self, settings: AutomatonSettings = AutomatonSettings(), corpus: Corpus = Corpus()):
        self.settings = settings
        rng = np.random.Generator(np.random.PCG64(settings.seed))
        grouped: dict[tuple[str, str], list[str]] = {}
        for kind, prefix, alphabet, (low, high) in FORMATS:
            letters = np.array(list(alphabet))
            for _ in range(settings.examples):
                body = "".join(letters[rng.integers(0, len(letters), int(rng.integers(low, high + 1)))])
                grouped.setdefault((kind, prefix), []).append(prefix + body)
        self.lengths = {prefix: (len(prefix) + low, len(prefix) + high) for _, prefix, _, (low, high) in FORMATS}
        self.dotted, self.dotted_shortest, dotted = self._dotted_jwt(rng)
        self.automata = [(kind, prefix, min(map(len, texts)), Automaton([symbols(t, max(settings.literal, len(prefix))) for t in texts], settings.alpha)) for (kind, prefix), texts in grouped.items()]
        some = [t for texts in grouped.values() for t in texts[: settings.examples // 4]] + dotted[: settings.examples // 4]
        self.general = GeneralModel(some, settings, corpus)

    def _dotted_jwt(self, rng: np.random.Generator) -> tuple[Automaton, int, list[str]]:
        """Automaton of header.payload.signature tokens; each letter is met at the literal places."""
        letters = np.array(list(_BASE62 + "_-"))
        samples = []
        for i in range(self.settings.examples):
            drawn = [letters[rng.integers(0, len(letters), int(rng.integers(low, high + 1)))] for low, high in JWT_PARTS]
            drawn[0][0] = letters[i % len(letters)]
            samples.append("eyJ" + ".".join("".join(part) for part in drawn))
        literal = max(self.settings.literal, len("eyJ"))
        return Automaton([symbols(t, literal) for t in samples], self.settings.alpha), len("eyJ") + 2 + sum(low for low, _ in JWT_PARTS), samples

    def score_dotted(self, token: str) -> tuple[str, float] | None:
        """As ``score``, for a token of three dotted segments."""
        if len(token) < self.dotted_shortest:
            return None
        sample = symbols(token, max(self.settings.literal, len("eyJ")))
        bits = (self.dotted.log_probability(sample) - self.background(sample)) / len(sample)
        return ("jwt", bits) if bits > -math.inf else None

    def background(self, sample: list[str]) -> float:
        """Log probability in a memoryless model of ordinary tokens (classes weighed as in prose)."""
        weigh = {"a": math.log2(0.8), "A": math.log2(0.08), "0": math.log2(0.08)}
        return sum(weigh.get("0" if s.isdigit() else "A" if s.isupper() else "a" if s.islower() else s, math.log2(0.01)) for s in sample)

    def score(self, token: str) -> tuple[str, float] | None:
        """(kind, bits per character over the background) of the likeliest format, if any accepts."""
        best = None
        for kind, prefix, shortest, automaton in self.automata:
            if not token.startswith(prefix) or len(token) < shortest:
                continue
            sample = symbols(token, max(self.settings.literal, len(prefix)))
            bits = (automaton.log_probability(sample) - self.background(sample)) / len(sample)
            if bits > (best[1] if best else -math.inf):
                best = (kind, bits)
        return best


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, rank of the kind, end) of base matches, leftmost and non-overlapping per kind, sorted."""
    found = [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= 6]
    found += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    found += [(m.start(), 2, m.end()) for m in HEX.finditer(text) if m.end() - m.start() >= 24]
    return sorted(found)


def _candidate(text: str, at: int, prefix: str, model: FormatModel) -> tuple[int, str] | None:
    """(end, kind) of the credential that starts with the format prefix at ``at``, if the automata accept one."""
    if prefix == "eyJ":
        m = _JWT.match(text, at)
        best = model.score_dotted(m[0]) if m else None
        if best and best[1] >= model.settings.threshold:
            return m.end(), best[0]
        if at and text[at - 1].isascii() and text[at - 1].isalnum():  # three letters inside some base64 say nothing
            return None
    token = _EXTENTS[prefix].match(text, at)[0]
    low, high = model.lengths[prefix]
    # A closing '-' or '_' belongs to the token where the alphabet has it, unless only the rest has a published length.
    cut = token.rstrip("-_")
    cut += token[len(cut) : low]
    ends = [cut] if len(token) > high and low <= len(cut) <= high and cut != token else [token, cut]
    for one in dict.fromkeys(ends):
        best = model.score(one)
        if best is not None and best[1] >= model.settings.threshold:
            return at + len(one), best[0]
    return None


def added_spans(text: str, base: list[tuple[int, int, int]], model: FormatModel) -> list[tuple[int, int, str]]:
    """Credentials outside base spans whose format likelihood passes the threshold, in order.

    Known formats come first: every place of a format's start is a candidate,
    wherever in a run of token characters it stands ('KEY=ghp_...',
    '?key=AIza...'); it reaches as far as the format's alphabet (for JWTs, over
    three dotted segments), the leftmost wins, and it has the format's kind.
    Then segments of runs that the general automaton takes for credentials are
    added where no span is yet, as kind ``credential``.
    """
    taken = _Spans(base)
    out = []
    done = 0
    for m in _PREFIX.finditer(text):
        start = m.start()
        if start < done:
            continue
        found = _candidate(text, start, m[0], model)
        if found is not None and not taken.meets(start, found[0]):
            out.append((start, *found))
            done = found[0]
    taken = _Spans(sorted(base + [(s, 0, e) for s, e, _ in out]))
    for run in _TOKEN.finditer(text):
        for a, b, _ in model.general.segments(run[0]) if run.end() - run.start() > 1 else ():
            start, end = run.start() + a, run.start() + b
            while end > start and text[end - 1] in "-_" + _SEPARATORS:
                end -= 1
            if not taken.meets(start, end) and not _UUID.fullmatch(text, start, end):
                out.append((start, end, "credential"))
    return sorted(out)


class _Spans:
    """Sorted spans (start, ., end) that may overlap, and whether others meet them."""

    def __init__(self, spans: list[tuple[int, int, int]]):
        self.starts = [s for s, _, _ in spans]
        self.reach, far = [], 0
        for _, _, e in spans:
            far = max(far, e)
            self.reach.append(far)

    def meets(self, start: int, end: int) -> bool:
        at = bisect.bisect_left(self.starts, end)
        return at > 0 and self.reach[at - 1] > start


def _long_run(raw: np.ndarray, borders: np.ndarray, table: np.ndarray, least: int) -> np.ndarray:
    """Rows that hold a run of ``least`` bytes of a class."""
    words = Words(raw, borders, table, lower=False)  # runs end where rows end
    starts = words.starts[words.ends - words.starts >= least]
    return np.unique(np.searchsorted(borders, starts, "right") - 1)


def _containing(data: bytes, borders: np.ndarray, cue: bytes) -> set[int]:
    rows, at = set(), data.find(cue)
    while at >= 0:
        row = int(np.searchsorted(borders, at, "right")) - 1
        rows.add(row)
        at = data.find(cue, int(borders[row + 1]))
    return rows


def _scan_kernel(shared):
    def run(batches):
        model: FormatModel = shared.value
        empty = hashlib.sha256(b"").hexdigest()
        for batch in batches:
            for part, raw, borders in slices(batch, "text"):
                low = LOWER[raw].tobytes()
                rows = set(_long_run(raw, borders, _HEX_BYTES, 24).tolist()) | set(model.general.may_pass(raw, borders).tolist())
                for cue in _CUES:
                    rows |= _containing(low, borders, cue)
                data = raw.tobytes()
                for cue in _STARTS:
                    rows |= _containing(data, borders, cue)
                n = part.num_rows
                counts = np.zeros((3, n), np.int64)
                digests, spans, added = [empty] * n, [""] * n, [0] * n
                for row in rows:
                    text = part.column(1)[row].as_py() or ""
                    base = base_spans(text)
                    for _, rank, _ in base:
                        counts[rank, row] += 1
                    named = [(s, r, f"{KINDS[r]}:{s}:{e}") for s, r, e in base]
                    digests[row] = hashlib.sha256(",".join(x[2] for x in named).encode()).hexdigest()
                    more = added_spans(text, base, model)
                    added[row] = len(more)
                    named += [(s, 3, f"{kind}:{s}:{e}") for s, e, kind in more]
                    spans[row] = ",".join(x[2] for x in sorted(named))
                yield pa.RecordBatch.from_arrays([part.column(0), *map(pa.array, counts), pa.array(digests), pa.array(spans), pa.array(added, pa.int64())], names=["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_added"])

    return run


def _token_kernel(batches):
    """(label, value): values of base spans (1) and other tokens (0), those of a batch once."""
    for batch in batches:
        labelled, other = set(), set()
        for text in batch.column(0).to_pylist():
            base = base_spans(text) if _HINT.search(text) else []
            if not base:
                other.update(_TOKEN.findall(text))
                continue
            taken = _Spans(base)
            labelled.update(m[2] for m in ASSIGN.finditer(text) if len(m[2]) >= 6)
            labelled.update(text[s:e] for s, rank, e in base if rank)
            other.update(m[0] for m in _TOKEN.finditer(text) if not taken.meets(m.start(), m.end()))
        yield pa.RecordBatch.from_arrays([pa.array([1] * len(labelled) + [0] * len(other), pa.int32()), pa.array([*labelled, *other], pa.string())], names=["label", "value"])


def _pair_kernel(batches):
    counts = np.zeros((_START + 1, _START), np.int64)
    for batch in batches:
        counts += _pairs(batch.column(0).to_pylist())
    at = np.flatnonzero(counts)
    yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(counts.ravel()[at])], names=["at", "n"])


def _prefix_kernel(depth: int):
    """(prefix, passed, ended) of the first ``depth`` places of labelled values."""

    def run(batches):
        for batch in batches:
            passed, ended = Counter(), Counter()
            for value in batch.column(0).to_pylist():
                pattern = _pattern(value)
                passed.update(pattern[:k] for k in range(min(len(pattern), depth) + 1))
                if len(pattern) <= depth:
                    ended[pattern] += 1
            yield pa.RecordBatch.from_arrays([pa.array([*passed], pa.string()), pa.array([*passed.values()], pa.int64()), pa.array([ended[p] for p in passed], pa.int64())], names=["prefix", "passed", "ended"])

    return run


def _tail_kernel(shared):
    """(prefix, c, d, n): steps out of the kept prefixes (d is null) and what follows them (prefix is null; d is -1 at the end)."""

    def run(batches):
        kept: frozenset[str] = shared.value
        for batch in batches:
            exits, tail = Counter(), Counter()
            for value in batch.column(0).to_pylist():
                pattern = _pattern(value)
                k = 0
                while k < len(pattern) and pattern[: k + 1] in kept:
                    k += 1
                if k < len(pattern):
                    rest = [_class_at(c) for c in pattern[k:]]
                    exits[pattern[:k], rest[0]] += 1
                    tail.update(zip(rest, [*rest[1:], -1], strict=True))
            rows = [(p, c, None, n) for (p, c), n in exits.items()] + [(None, c, d, n) for (c, d), n in tail.items()]
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate((pa.string(), pa.int32(), pa.int32(), pa.int64()))], names=["prefix", "c", "d", "n"])

    return run


def _gain_kernel(shared):
    def run(batches):
        model: GeneralModel = shared.value
        found = Counter()
        for batch in batches:
            found.update(min(math.ceil(model.best(t) * _BINS), _MOST_BINS) for t in batch.column(0).to_pylist())
        yield pa.RecordBatch.from_arrays([pa.array([*found], pa.int32()), pa.array([*found.values()], pa.int64())], names=["at", "n"])

    return run


def train(spark: SparkSession, docs: DataFrame, settings: AutomatonSettings = AutomatonSettings()) -> FormatModel:
    """A model inferred from the formats and from the whole corpus.

    Every distinct value of a base span and every distinct other token of every
    text counts, of the latter half for the background and half (told by their
    hash) for the threshold.  The corpus's labelled values weigh as ``labelled``
    examples together where they are more, and a prefix that so many cannot tell
    from others is not a node of its own; so at most about a hundred nodes a place
    are kept.  Deterministic; an empty corpus leaves the formats and the generated
    ordinary tokens.
    """
    work = Workspace(spark, "secrets")
    texts = docs.select(F.col("text").cast("string").alias("text")).where("text is not null")
    seen = work.table("seen", texts.mapInArrow(_token_kernel, "label int, value string").distinct())
    labelled = seen.where("label = 1").select("value")
    half = lambda k: seen.where("label = 0").where(F.pmod(F.xxhash64("value", F.lit(settings.seed)), F.lit(2)) == k).select("value")
    pairs = np.zeros((_START + 1) * _START, np.int64)
    for r in half(0).mapInArrow(_pair_kernel, "at int, n long").groupBy("at").agg(F.sum("n").alias("n")).collect():
        pairs[r.at] = r.n
    total = labelled.count()
    weight = min(1.0, settings.labelled / max(1, total))
    counted = labelled.mapInArrow(_prefix_kernel(settings.depth), "prefix string, passed long, ended long").groupBy("prefix").agg(F.sum("passed").alias("passed"), F.sum("ended").alias("ended"))
    least = merge_bound(settings.alpha) ** 2 / weight if total > settings.labelled else 0.0
    nodes = {r.prefix: (weight * r.passed, weight * r.ended) for r in counted.where((F.col("passed") > least) | (F.col("prefix") == "")).collect()}
    kept = spark.sparkContext.broadcast(frozenset(nodes))
    steps = labelled.mapInArrow(_tail_kernel(kept), "prefix string, c int, d int, n long").groupBy("prefix", "c", "d").agg(F.sum("n").alias("n")).collect()
    exits = {(r.prefix, r.c): weight * r.n for r in steps if r.d is None}
    tail = {(r.c, r.d): weight * r.n for r in steps if r.d is not None}
    corpus = Corpus(nodes, exits, tail, pairs.reshape(_START + 1, _START))
    shared = spark.sparkContext.broadcast(FormatModel(settings, corpus).general)
    gains = half(1).mapInArrow(_gain_kernel(shared), "at int, n long").groupBy("at").agg(F.sum("n").alias("n")).collect()
    work.close()
    return FormatModel(settings, replace(corpus, gains=tuple((r.at, r.n) for r in gains)))


def scan(spark: SparkSession, docs: DataFrame, settings: AutomatonSettings = AutomatonSettings(), model: FormatModel | None = None) -> DataFrame:
    """doc_id, counts per base kind, digest of base spans, all spans, and ``n_added`` of every whole text.

    Null text counts as empty; documents without spans have zero counts, the
    digest of the empty string and empty spans; repeated rows give equal rows,
    with or without doc_id; an empty table gives none; extra columns are
    ignored, whatever their names.  One narrow pass after the training.
    """
    model = model or train(spark, docs, settings)
    shared = spark.sparkContext.broadcast(model)  # a few automata of bounded size
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    schema = "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_added long"
    return rows.mapInArrow(_scan_kernel(shared), schema)
