"""Online pattern-class automaton over a segment of items, with id sets.

Used where patterns have no length limit and for insertion symbol by symbol. A state is a class of patterns;
``span`` is the length of its longest member, ``up`` its suffix link. Items never share a pattern across their
boundary: every item starts at the root again. A split copies the items of the state it comes from.
"""

from __future__ import annotations

from collections.abc import Iterable

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


class LocalAutomaton:
    """States are numbers. A state's longest member is kept as where it ends: item, place and length."""

    def __init__(self) -> None:
        self.span, self.up, self.next, self.ids, self.ends = [0], [-1], [{}], [set()], [(None, -1)]
        self.seqs: dict[int, str] = {}
        self.split_from: list[tuple[int, int]] = []  # (new, old) since it was last emptied

    def _new(self, span: int, up: int, end: tuple[int, int], like: int | None = None) -> int:
        self.span.append(span)
        self.up.append(up)
        self.ends.append(end)
        self.next.append({} if like is None else dict(self.next[like]))
        self.ids.append(set() if like is None else set(self.ids[like]))
        return len(self.span) - 1

    def name(self, state: int) -> str:
        """The longest member."""
        item, at = self.ends[state]
        return "" if state == 0 else self.seqs[item][at + 1 - self.span[state] : at + 1]

    def _split(self, p: int, symbol: str, q: int) -> int:
        """The part of q that ends where p's extension ends; q itself if it is no longer than that."""
        if self.span[q] == self.span[p] + 1:
            return q
        c = self._new(self.span[p] + 1, self.up[q], self.ends[q], q)
        self.split_from.append((c, q))
        self.up[q] = c
        while p >= 0 and self.next[p].get(symbol) == q:
            self.next[p][symbol] = c
            p = self.up[p]
        return c

    def extend(self, last: int, symbol: str, end: tuple[int, int]) -> int:
        """The state of the prefix that ends at ``end`` with ``symbol``, after state ``last``."""
        if symbol in self.next[last]:
            return self._split(last, symbol, self.next[last][symbol])
        new, p = self._new(self.span[last] + 1, 0, end), last
        while p >= 0 and symbol not in self.next[p]:
            self.next[p][symbol] = new
            p = self.up[p]
        if p >= 0:
            self.up[new] = self._split(p, symbol, self.next[p][symbol])
        return new

    def propagate(self, state: int, item: int) -> list[int]:
        """Give the item to the state and up the links until one has it; the states that are new to it."""
        touched = []
        while state > 0 and item not in self.ids[state]:
            self.ids[state].add(item)
            touched.append(state)
            state = self.up[state]
        self.ids[0].add(item)
        return touched

    def add(self, item: int, seq: str | None) -> list[int]:
        """The states whose ids the item joins, in the order in which it does."""
        self.ids[0].add(item)
        self.seqs[item] = seq or ""
        last, touched = 0, []
        for i, symbol in enumerate(seq or ""):
            last = self.extend(last, symbol, (item, i))
            touched += self.propagate(last, item)
        return touched

    def locate(self, pattern: str) -> int | None:
        at = 0
        for symbol in pattern:
            at = self.next[at].get(symbol, -1)
            if at < 0:
                return None
        return at

    def order(self) -> list[int]:
        """States, every state after all that it leads to."""
        seen, out = [0] * len(self.span), []
        stack = [(0, iter(self.next[0].values()))]
        seen[0] = 1
        while stack:
            s, it = stack[-1]
            t = next(it, None)
            if t is None:
                out.append(s)
                stack.pop()
            elif not seen[t]:
                seen[t] = 1
                stack.append((t, iter(self.next[t].values())))
        return out

    def donors(self) -> tuple[dict[int, int], dict[int, set[int]]]:
        """(donor, residual ids) of each state: the largest residual anywhere below; ties to the shorter, then older state."""
        donor: dict[int, int] = {}
        held: dict[int, set[int]] = {}
        best: dict[int, int] = {}
        for s in self.order():
            below = {best[t] for t in self.next[s].values()}
            if below:
                donor[s] = min(below, key=lambda t: (-len(held[t]), self.span[t], t))
            held[s] = self.ids[s] - held[donor[s]] if s in donor else set(self.ids[s])
            best[s] = min({s, *([donor[s]] if s in donor else [])}, key=lambda t: (-len(held[t]), self.span[t], t))
        return donor, held


def build(items: Iterable[tuple[int, str | None]]) -> LocalAutomaton:
    a = LocalAutomaton()
    for item, seq in items:
        a.add(item, seq)
    return a


class OnlineIndex:
    """Raw lists over an automaton that stay an exact cover while items come one by one.

    An item that joins a state goes into the state's own list only if the donor's list does not give it; states
    that are led to come first, so that a donor's list is settled before its heirs look. A state that a split has
    made since has no list yet: it is served by all its ids until lists are built anew.
    """

    def __init__(self, automaton: LocalAutomaton):
        self.a = automaton
        self.rebuild()

    def rebuild(self) -> None:
        self.donor, self.held = self.a.donors()
        self.heirs: dict[int, list[int]] = {}
        for s, t in self.donor.items():
            self.heirs.setdefault(t, []).append(s)
        self.fresh: set[int] = set()

    def insert(self, item: int, seq: str | None) -> list[int]:
        before = len(self.a.span)
        self.a.split_from.clear()
        touched = set(self.a.add(item, seq))
        self.fresh |= set(range(before, len(self.a.span)))
        for s in sorted({0, *touched} - self.fresh, key=lambda s: -self.a.span[s]):  # a state leads to longer ones only
            if item not in self.held.get(self.donor.get(s), ()):
                self.held[s].add(item)
        return sorted(touched)

    def changed_by(self, touched: Iterable[int]) -> set[int]:
        """States whose cover may differ once ``touched`` ones do: these, the root, and those that one of them is the donor of."""
        return {0, *touched, *(h for s in touched for h in self.heirs.get(s, ()))}

    def cover(self, state: int) -> tuple[set[int], set[int]]:
        """(own, donor's) ids of a state."""
        if state in self.fresh:
            return set(self.a.ids[state]), set()
        return self.held[state], self.held[self.donor[state]] if state in self.donor else set()

    def wrong(self, states: Iterable[int]) -> int:
        """How many of the states have a list, their own with the donor's, that is not exact or not disjoint."""
        count = 0
        for s in states:
            own, given = self.cover(s)
            count += len(own) + len(given) != len(self.a.ids[s]) or not (own <= self.a.ids[s] and given <= self.a.ids[s] and own.isdisjoint(given))
        return count

    def matches(self, pattern: str) -> set[int]:
        state = self.a.locate(pattern)
        return set() if state is None else set.union(*self.cover(state))


#: Symbols that a task's automaton is built over, about; an automaton takes a few hundred bytes a symbol.
SEGMENT_SYMBOLS = 2_000_000


def dealt(corpus: DataFrame, segments: int | None) -> DataFrame:
    """(segment, id, seq) by id hash; without ``segments``, as many as the symbols ask for."""
    if segments is None:
        total = corpus.agg(F.sum(F.char_length("seq"))).first()[0] or 0
        segments = max(1, -(-total // SEGMENT_SYMBOLS))
    return corpus.select(F.pmod(F.xxhash64("id"), F.lit(segments)).cast("int").alias("segment"), "id", "seq")


def segment_tables(corpus: DataFrame, segments: int | None = None, names: bool = True) -> DataFrame:
    """(segment, state, link, span, n_ids, n_held, donor, n_next) of an automaton for each segment of items.

    Segments are independent, each is built in one task, items sorted by id. States are written as their longest
    members, which for long sequences is far more than the automaton; without ``names`` as item:end:length.
    """
    schema = "segment int, state string, link string, span int, n_ids long, n_held long, donor string, n_next int"

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("id")
        a = build(zip(pdf["id"], pdf["seq"], strict=True))
        donor, held = a.donors()
        name = a.name if names else lambda s: "{}:{}:{}".format(*a.ends[s], a.span[s]) if s else ""
        rows = [(int(pdf["segment"].iloc[0]), name(s), name(a.up[s]) if s else None, a.span[s], len(a.ids[s]), len(held[s]), name(donor[s]) if s in donor else None, len(a.next[s])) for s in range(len(a.span))]
        return pd.DataFrame(rows, columns=[c.split()[0] for c in schema.split(", ")])

    return dealt(corpus, segments).groupBy("segment").applyInPandas(run, schema)


def segment_matches(corpus: DataFrame, queries: DataFrame, segments: int | None = None) -> DataFrame:
    """(qid, id): items of each pattern, of any length, by walking every segment's automaton to its state and its donor's list."""
    asked = [(r["qid"], r["pattern"]) for r in queries.select("qid", "pattern").collect()]

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        index = OnlineIndex(build(zip(pdf["id"], pdf["seq"], strict=True)))
        rows = [(q, i) for q, p in asked for i in sorted(index.matches(p))]
        return pd.DataFrame(rows, columns=["qid", "id"])

    return dealt(corpus, segments).groupBy("segment").applyInPandas(run, "qid long, id long")
