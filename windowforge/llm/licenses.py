"""License scans: phrases by word, and templates whose optional and replaceable regions are compiled into token automata."""

from __future__ import annotations

import re
from dataclasses import dataclass
from functools import lru_cache

from pyspark.sql import DataFrame

from .common import by_text
from .license_texts import TEMPLATES

#: Phrases and their labels.
PHRASES = {"mit license": "mit", "apache license": "apache", "general public license": "gpl"}
_SEPARATORS = bytes(b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else b + 32 if 65 <= b <= 90 else 32 for b in range(256))


def words_of(text: str) -> list[bytes]:
    """Words of the lower-cased text: letters a-z, digits and everything outside ASCII."""
    return text.encode().translate(_SEPARATORS).split()


@dataclass(frozen=True)
class Word:
    word: bytes


@dataclass(frozen=True)
class Any:
    """``least`` to ``most`` words of any kind."""

    least: int
    most: int


@dataclass(frozen=True)
class Optional:
    """One of some sequences of regions, or none of them."""

    choices: tuple[tuple, ...]


def parse(template: str) -> tuple[Word | Any | Optional, ...]:
    """The regions of a template, which may hold regions in turn."""
    parts = re.findall(r"\{\d+-\d+\}|[\[\]|]|[^\s\[\]{}|]+", template)

    def regions(at: int, depth: int) -> tuple[list, int]:
        """All alternatives up to the closing bracket, and the place behind it."""
        choices, now = [], []
        while at < len(parts):
            part = parts[at]
            at += 1
            if part == "[":
                inner, at = regions(at, depth + 1)
                inner = [tuple(c) for c in inner if c]
                if inner:
                    now.append(Optional(tuple(inner)))
            elif part == "]":
                if not depth:
                    raise ValueError("a region ends that never began")
                return [*choices, now], at
            elif part == "|" and depth:
                choices.append(now)
                now = []
            elif part[0] == "{":
                low, high = part[1:-1].split("-")
                now.append(Any(int(low), int(high)))
            else:
                now += [Word(w) for w in words_of(part)]
        if depth:
            raise ValueError("a region has no end")
        return [now], at

    return tuple(regions(0, 0)[0][0])


class Automaton:
    """Finds word sequences that hold all mandatory words in their places. States are numbers; ``None`` labels a step over any word."""

    def __init__(self, template: str):
        self.steps: list[dict[bytes | None, set[int]]] = [{}]
        self.free: list[set[int]] = [set()]
        regions = parse(template)
        self.needs = {r.word for r in regions if isinstance(r, Word)}
        if not self.needs:
            raise ValueError("a template without a mandatory word stands everywhere")
        self.last = self._add(regions, 0)
        self.begin = self._closed({0})

    def _add(self, regions: tuple, at: int) -> int:
        """States for a sequence of regions from a state on; the state where it ends."""
        for r in regions:
            if isinstance(r, Word):
                at = self._step(at, r.word)
            elif isinstance(r, Any):
                ends = []
                for k in range(r.most):
                    if k >= r.least:
                        ends.append(at)
                    at = self._step(at, None)
                for e in ends:
                    self.free[e].add(at)
            else:
                ends = [at, *(self._add(c, self._free(at)) for c in r.choices)]
                at = self._new()
                for e in ends:
                    self.free[e].add(at)
        return at

    def _new(self) -> int:
        self.steps.append({})
        self.free.append(set())
        return len(self.steps) - 1

    def _free(self, at: int) -> int:
        """A new state that is reached from another without a word, so that choices do not grow into each other."""
        new = self._new()
        self.free[at].add(new)
        return new

    def _step(self, at: int, word: bytes | None) -> int:
        new = self._new()
        self.steps[at].setdefault(word, set()).add(new)
        return new

    def _closed(self, states: set[int]) -> set[int]:
        out, todo = set(), list(states)
        while todo:
            s = todo.pop()
            if s not in out:
                out.add(s)
                todo += self.free[s]
        return out

    def found(self, words: list[bytes]) -> bool:
        """Whether the template stands somewhere. One pass: a new attempt begins at each word beside those under way, and attempts that
        meet in a state go on as one, so that the time is bounded by words times states."""
        states: set[int] = set()
        for word in words:
            reached: set[int] = set()
            for s in states | self.begin:
                step = self.steps[s]
                reached |= step.get(word, _NONE)
                reached |= step.get(None, _NONE)
            states = self._closed(reached) if reached else reached
            if self.last in states:
                return True
        return False


_NONE: frozenset[int] = frozenset()
Compiled = list[tuple[str, Automaton]]


def compiled(templates: dict[str, list[str]]) -> Compiled:
    return [(label, Automaton(t)) for label, ts in templates.items() for t in ts]


@lru_cache(maxsize=1)
def automata() -> Compiled:
    """The known licences and notices."""
    return compiled(TEMPLATES)


def scan(text: str, known: Compiled | None = None) -> tuple[int, list[tuple[int, str]], set[str]]:
    """Words of a text, places of the base phrases, labels of the templates."""
    words = words_of(text)
    places: dict[bytes, list[int]] = {}
    have = set(words)
    base: list[tuple[int, str]] = []
    phrases = [(p.encode().split(), label) for p, label in PHRASES.items()]
    due = [(label, a) for label, a in (automata() if known is None else known) if a.needs <= have]
    if any(set(p) <= have for p, _ in phrases):
        for i, w in enumerate(words):
            places.setdefault(w, []).append(i)
        for p, label in phrases:
            base += [(i, label) for i in places.get(p[0], ()) if words[i : i + len(p)] == p]
    return len(words), sorted(base), {label for label, a in due if a.found(words)}


def license_scan(docs: DataFrame, templates: dict[str, list[str]] | None = None) -> DataFrame:
    """Per row: doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score.

    score is 1 where a template's whole mandatory wording stands, 0.5 where only a base phrase does, else 0. Null and
    empty texts have no words and empty labels; very long texts are scanned whole, in one pass. Repeated rows give repeated
    results, rows without an id one without it, an empty table an empty one; other columns are ignored. ``templates``, by
    label, take the place of the known ones.
    """
    known = compiled(templates) if templates is not None else None

    def tell(texts: list[str]) -> list[tuple]:
        rows = []
        for text in texts:
            n, base, found = scan(text, known)
            mine = sorted({label for _, label in base})
            rows.append((n, len(base), base[0][0] if base else None, base[-1][0] if base else None, ",".join(mine), ",".join(sorted({*mine, *found})), 1.0 if found else 0.5 if base else 0.0))
        return rows

    return by_text(docs, "doc_id", "text", "n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double", lambda: tell)


def template_pattern(template: str) -> str:
    """The template as a regular expression over words that each end with a space, after one leading space; for checks by other engines."""

    def of(regions: tuple) -> str:
        out = ""
        for r in regions:
            if isinstance(r, Any):
                out += "([^ ]+ ){%d,%d}" % (r.least, r.most)
            elif isinstance(r, Word):
                out += r.word.decode() + " "
            else:
                out += "(" + "|".join(of(c) for c in r.choices) + ")?"
        return out

    return " " + of(parse(template))
