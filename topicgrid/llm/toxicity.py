"""Toxicity by a weighted finite-state pattern grammar.

A lexer turns words and marks into classes. Five transducers read them: reported speech marks what quotation marks or a verb of
saying govern, negation marks the next words, the target machine tells at a clause's end whether the clause names someone (before
or after), the insult and the threat machine each take up their own words and tell at the clause's end which they had. They are composed
into one machine, which writes at the end of a clause what kind of clause matched; a clause that is one lone word matches nothing.
Weights of the kinds of clause, and of words inside clauses that assert them, are learned from labels.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import ahocorasick
import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame

from topicgrid.llm.common import Passing, blocks, mix64, tidy
from topicgrid.llm.quality import labelled_sample

#: Words of each class (lower case).
INSULTS = "idiot idiots moron morons stupid dumb clown clowns loser losers trash scum worthless pathetic disgusting filth filthy vermin garbage imbecile cretin fool fools jerk pig pigs dimwit degenerate parasite subhuman idiota imbécil estúpido basura idiote imbécile stupide ordure dummkopf trottel abschaum".split()
THREATS = "kill murder hurt destroy strangle shoot stab burn beat crush slaughter hang".split()
TARGETS = "you your yours u he she they them him her his their these those this that i we vous toi tu il elle ils usted tú ellos du ihr sie".split()
NEGATIONS = "not no never n't nobody none isn't aren't wasn't don't doesn't nicht kein keine nie ne pas jamais nunca jamás".split()
REPORTS = "said says say called calls claimed claims wrote writes quoted quote reported tweeted alleged sagte dit dijo".split()

PIECE = re.compile(r"[^\W_]+(?:['’][^\W_]+)?|[\"“”„«»]|[.!?;]")
OTHER, INSULT, THREAT, TARGET, NEG, REPORT, QUOTE, CLOSE, END, BREAK = range(10)
KINDS = range(10)
CLASS = {w: c for c, ws in ((TARGET, TARGETS), (NEG, NEGATIONS), (REPORT, REPORTS), (THREAT, THREATS), (INSULT, INSULTS)) for w in ws} | dict.fromkeys("\"“„«»", QUOTE) | {"”": CLOSE} | dict.fromkeys(".!?;", END)
TRIGGERS = INSULTS + THREATS
NEGATED, REPORTED = 1, 2  # flags of a trigger
SCOPE = 3  # words that a negation governs


@dataclass(frozen=True)
class Transducer:
    """A deterministic machine: ``step(state, symbol)`` gives the next state and the symbol that it writes."""

    start: object
    step: object

    def then(self, other: Transducer) -> Transducer:
        """Composition: the other one reads what this one writes."""

        def step(state, symbol):
            a, mid = self.step(state[0], symbol)
            b, out = other.step(state[1], mid)
            return (a, b), out

        return Transducer((self.start, other.start), step)

    def compiled(self, alphabet) -> tuple[list[dict], int]:
        """All reachable states numbered, with their transitions."""
        number, rows, todo = {self.start: 0}, [], [self.start]
        while todo:
            state = todo.pop(0)
            row = {}
            for s in alphabet:
                to, out = self.step(state, s)
                if to not in number:
                    number[to] = len(number)
                    todo.append(to)
                row[s] = (number[to], out)
            rows.append(row)
        return rows, 0


def _marked(symbol, flag: int):
    kind, note = symbol
    return (kind, note | flag) if kind in (INSULT, THREAT) else symbol


def _reporting(state, symbol):
    """Inside quotation marks, which may span clauses of a line, and after a verb of saying, to the clause's end."""
    quoted, said = state
    kind = symbol[0]
    if kind == QUOTE:
        return (not quoted, said), symbol
    if kind == CLOSE:
        return (False, said), symbol
    if kind == REPORT:
        return (quoted, True), symbol
    if kind == END:
        return (quoted, False), symbol
    if kind == BREAK:
        return (False, False), symbol
    return state, _marked(symbol, REPORTED) if quoted or said else symbol


def _negating(left: int, symbol):
    """The next three words after a negation."""
    kind = symbol[0]
    if kind == NEG:
        return SCOPE, symbol
    if kind in (END, BREAK):
        return 0, symbol
    if kind in (QUOTE, CLOSE):
        return left, symbol
    return max(0, left - 1), _marked(symbol, NEGATED) if left else symbol


def _targeting(seen: bool, symbol):
    """At a clause's end: whether it names someone, wherever that was."""
    kind = symbol[0]
    if kind == TARGET:
        return True, symbol
    if kind in (END, BREAK):
        return False, (kind, int(seen))
    return seen, symbol


def _finding(own: int):
    """The machine of insults, or of threats: keeps its mildest flags and adds them to what is told at the end (5 values: none, or flags + 1)."""

    def step(state: int, symbol):
        kind, note = symbol
        if kind == own:
            return min(state, note + 1) if state else note + 1, (OTHER, 0)
        if kind in (END, BREAK):
            return 0, (kind, note * 5 + state)
        return state, symbol

    return step


def _closing(words: int, symbol):
    """Writes the kind of clause at its end, or nothing: no trigger in it, or nothing but one word."""
    kind, note = symbol
    if kind in (END, BREAK):
        told = note % 25
        return 0, note if told and words > 1 else None
    return (words if kind in (QUOTE, CLOSE) else min(2, words + 1)), None


MACHINE = Transducer((False, False), _reporting).then(Transducer(0, _negating)).then(Transducer(False, _targeting)).then(Transducer(0, _finding(INSULT))).then(Transducer(0, _finding(THREAT))).then(Transducer(0, _closing))
PATTERNS = 50  # target (2) by insult (5) by threat (5)
ROWS, _ = MACHINE.compiled([(k, 0) for k in KINDS])
#: What a trigger's word counts by: its flags, which the first two machines give it.
FLAGS, _ = Transducer((False, False), _reporting).then(Transducer(0, _negating)).compiled([(k, 0) for k in KINDS])
STEM = range(3, 11)


def parts_of(pattern: int) -> tuple[int, int, int]:
    """Target (0, 1), insult and threat (0: none, else 1 + flags) of a kind of clause."""
    return pattern // 25, pattern // 5 % 5, pattern % 5


class Lexicon:
    """Listed words, and insult stems learned from labels: a word that starts with a stem is read as an insult."""

    def __init__(self, stems: tuple[str, ...] = ()):
        self.stems = tuple(sorted(stems))
        self.at = {w: PATTERNS + k for k, w in enumerate([*TRIGGERS, *self.stems])}
        self.more = PATTERNS + len(self.at)  # two, and three or more clauses that assert an insult or a threat
        self.n_features = self.more + 2

    def matcher(self) -> ahocorasick.Automaton:
        found = ahocorasick.Automaton()
        for w in TRIGGERS:
            found.add_word(w, (len(w), True))
        for w in self.stems:
            if w not in CLASS:
                found.add_word(w, (len(w), False))
        found.make_automaton()
        return found

    def read(self, word: str) -> tuple[int, str]:
        """Class of a word, and the entry that gave it."""
        if (c := CLASS.get(word)) is not None:
            return c, word
        if self.stems:
            for n in STEM:
                if word[:n] in self.at and len(word) >= n and word[:n] not in CLASS:
                    return INSULT, word[:n]
        return OTHER, word

    def features(self, text: str, triggers: ahocorasick.Automaton) -> dict[int, float] | None:
        """Kinds of matched clauses, the words asserted in them, each counted up to 3; nothing where no clause matches.

        Only lines that hold a trigger run through the machine, each once.
        """
        low = text.lower()
        done, out, asserted = 0, {}, 0
        for end, (n, whole) in triggers.iter(low):
            at = end - n + 1
            if at < done or (at and low[at - 1].isalnum()) or (whole and end + 1 < len(low) and low[end + 1].isalnum()):
                continue
            begin = max(done, low.rfind("\n", done, at) + 1)
            stop = low.find("\n", end)
            done = stop + 1 if stop >= 0 else len(low)
            state = flags = 0
            words: list[int] = []
            for piece in PIECE.finditer(low, begin, done):
                kind, entry = self.read(piece.group())
                state, match = ROWS[state][(kind, 0)]
                flags, (_, note) = FLAGS[flags][(kind, 0)]
                if kind in (INSULT, THREAT):
                    if not note:
                        words.append(self.at[entry])
                elif kind == END:
                    asserted += self._clause(match, words, out)
                    words = []
            asserted += self._clause(ROWS[state][(BREAK, 0)][1], words, out)
        if asserted > 1:
            out[self.more + (asserted > 2)] = 1.0
        return out or None

    @staticmethod
    def _clause(match: int | None, words: list[int], out: dict[int, float]) -> bool:
        """Count a clause's kind and asserted words; whether it asserts something."""
        if match is None:
            return False
        for k in (match, *words):
            out[k] = min(3.0, out.get(k, 0.0) + 1)
        return bool(words)


def distinct_texts(texts: list[bytes]) -> list[int]:
    """Rows without near copies of earlier ones: five bands of three minima of word hashes, none shared."""
    seen: set = set()
    out = []
    salts = np.random.default_rng(3).integers(1, 2**63, 15, dtype=np.uint64) | np.uint64(1)
    for k, t in enumerate(texts):
        words = np.array([xxhash.xxh3_64_intdigest(w) for w in set(t.split())] or [0], np.uint64)
        mins = [mix64(words * s).min() for s in salts]
        bands = {(j, *mins[j : j + 3]) for j in range(0, 15, 3)}
        if not bands & seen:
            out.append(k)
        seen |= bands
    return out


def learned_stems(texts: list[bytes], labels: np.ndarray, support: int = 8, precision: float = 0.8, most: int = 200) -> tuple[str, ...]:
    """Beginnings of words that nearly only toxic texts have: the shortest of each family, at most ``most`` by support."""
    has: list[Counter[str]] = [Counter(), Counter()]
    for t, y in zip(texts, labels.tolist(), strict=True):
        has[y].update({w[:n] for w in set(PIECE.findall(t.decode(errors="replace").lower())) for n in STEM if n <= len(w)})
    good = {s for s, n in has[1].items() if n >= support and n / (n + has[0][s]) >= precision and s not in CLASS}
    shortest = [s for s in good if not any(s[:n] in good for n in range(STEM.start, len(s)))]
    listed = tuple(TRIGGERS)
    new = [s for s in shortest if not any(w.startswith(s) or s.startswith(w) for w in listed)]
    return tuple(sorted(new, key=lambda s: (-has[1][s], s))[:most])


class ToxicityGrammar:
    """The lexicon, and weights of kinds of clause and of words, and the base rate."""

    def __init__(self, lexicon: Lexicon | None = None):
        self.lexicon = lexicon or Lexicon()
        # before any label: an asserted insult counts, more if aimed at someone; a threat counts only if it is; what is denied or reported counts less
        self.prior = np.zeros(self.lexicon.n_features)
        worth = (0.0, 1.0, 0.3, 0.4, 0.1)  # none, asserted, negated, reported, both
        for k in range(PATTERNS):
            target, insult, threat = parts_of(k)
            self.prior[k] = (4.0 + 1.5 * target) * worth[insult] + 4.0 * target * worth[threat]
        self.weights, self.base = self.prior.copy(), -3.0

    def fit(self, texts: list[bytes], labels: np.ndarray, ridge: float = 0.05, rounds: int = 25) -> ToxicityGrammar:
        """Stems from texts that aren't near copies; weights by Newton steps of a logistic regression, drawn towards the prior."""
        own = distinct_texts(texts)
        self.__init__(Lexicon(learned_stems([texts[k] for k in own], labels[own])))
        triggers = self.lexicon.matcher()
        x = np.zeros((len(texts), self.lexicon.n_features + 1))
        x[:, -1] = 1
        for r, t in enumerate(texts):
            for k, v in (self.lexicon.features(t.decode(errors="replace"), triggers) or {}).items():
                x[r, k] = v
        start = np.append(self.prior, self.base)
        w, pull = start.copy(), np.append(np.full(len(self.prior), ridge * 20), ridge)
        for _ in range(rounds):
            p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
            g = x.T @ (p - labels) + pull * (w - start)
            h = (x * (p * (1 - p))[:, None]).T @ x + np.diag(pull)
            w = w - np.clip(np.linalg.solve(h, g), -2, 2)
        self.weights, self.base = w[:-1], float(w[-1])
        return self

    def score(self, found: dict[int, float] | None) -> float:
        z = self.base + sum(self.weights[k] * v for k, v in (found or {}).items())
        return float(1 / (1 + np.exp(-np.clip(z, -40, 40))))


def train_toxicity(docs: DataFrame, labels: DataFrame, most: int = 8000) -> ToxicityGrammar:
    """Weights learned from at most ``most`` labelled rows of the training folds; none: the prior."""
    t, y = labelled_sample(docs, labels, "toxic", most)
    return ToxicityGrammar().fit(t, y) if len(t) else ToxicityGrammar()


def score_toxicity(docs: DataFrame, grammar: ToxicityGrammar, text_col: str = "text", threshold: float = 0.5) -> DataFrame:
    """``docs`` with score, predicted (1 where score is at least ``threshold``) and n_matches (kinds of clause that matched).

    Whole texts are read; null counts as empty and gets the base rate. Rows that repeat get equal scores, an empty table gives an
    empty one. A very long text is read line by line, but only lines that hold a listed word or stem. Columns named like the three, in any
    case, are replaced, all others pass through.
    """
    own = Passing.of(docs, [text_col], ("score", "predicted", "n_matches"))
    at, held = own.at[text_col], docs.sparkSession.sparkContext.broadcast(grammar)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lexicon = held.value.lexicon
        triggers = lexicon.matcher()
        for batch in blocks(batches, at):
            found = [lexicon.features(t or "", triggers) for t in batch.column(at).to_pylist()]
            p = np.array([held.value.score(x) for x in found])
            n = pa.array([sum(k < PATTERNS for k in x or ()) for x in found], pa.int32())
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(p), pa.array((p >= threshold).astype(np.int32)), n], names=[*batch.schema.names, "score", "predicted", "n_matches"])

    return own.returned(own.frame.mapInArrow(tidy(run), own.schema.add("score", "double").add("predicted", "integer").add("n_matches", "integer")))
