"""Token counts from a deterministic transducer compiled out of a piece vocabulary.

The transducer reads characters. After each prefix its running sum of emitted counts is the number of
tokens the vocabulary's greedy merges give for that prefix, so a transition carries the change of that
number. A state holds what the future can depend on: for each suffix of the text read that could grow
into a longer piece, the piece that ends before that suffix and the count there. The next last piece
is the one whose neighbour on its left stays unmerged beside it; that test runs the merges on two
pieces and is remembered. States and transitions are compiled when first needed and kept in a bounded
table. Between two characters that no piece holds side by side nothing ever merges, so the machine is
back at its start there.

Every text of more than one chunk is counted by state maps. The map of a chunk is a table from entry
states to exit state and count. Its first row is for the state that the end of the chunk before leads to
when read from the start, which is nearly always the true one; other rows are added when a composition
asks for them, each once. Behind the first boundary of a chunk all entries go on alike, so only what
precedes it is read again. Maps compose associatively: a reduction in a balanced tree gives a text's
count, a prefix scan in doubling steps the count at the end of every chunk. States are kept by value, so
maps outlive the compiled table, and what is held is a table row for each chunk, whatever the text.

Defined results: null counts as empty text, which has no tokens; n_bytes is the length in UTF-8;
columns besides doc_id and text are ignored; of repeated rows each is counted.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import map_batches, texts

MARK = "▁"
#: A state: (suffix, piece that ends before it, count there less the count here) for each suffix that can grow.
State = tuple[tuple[str, str, int], ...]
START: State = (("", "", 0),)
#: Transitions a worker compiles, and segments it remembers, before it starts anew; results never depend on it.
COMPILED, REMEMBER = 400_000, 200_000
#: Longest segment that is remembered, in characters.
SHORT = 64
#: Characters of a chunk, and of the end of the chunk before that tell its likely entry state.
CHUNK, OVERLAP = 1 << 12, 64

SCHEMA = "doc_id long, n_bytes long, n_tokens long, over_limit boolean"


@dataclass(frozen=True)
class Vocabulary:
    """Pieces with their merge scores, and whether a mark goes before a text."""

    scores: dict[str, float]
    add_prefix: bool = True


def read_model(path: str) -> Vocabulary:
    """Normal pieces of a published model file of the BPE kind with byte fallback and no normalisation rules."""
    from sentencepiece import sentencepiece_model_pb2 as model

    proto = model.ModelProto()
    with open(path, "rb") as file:
        proto.ParseFromString(file.read())
    rules = proto.normalizer_spec
    if proto.trainer_spec.model_type != 2 or not proto.trainer_spec.byte_fallback or rules.precompiled_charsmap or rules.remove_extra_whitespaces:
        raise ValueError("only BPE models with byte fallback and identity normalisation are compiled")
    return Vocabulary({p.piece: p.score for p in proto.pieces if p.type == 1}, rules.add_dummy_prefix)


class StateMap:
    """Exit state and count by entry state, of a chunk or of two maps one after the other."""

    __slots__ = ("first", "head", "rest", "rows", "then")

    def __init__(self, head: str = "", rest: tuple[State, int] | None = None, first: StateMap | None = None, then: StateMap | None = None):
        self.rows: dict[State, tuple[State, int]] = {}
        #: Of a chunk: the text before its first boundary, and exit state and count of what follows it.
        self.head, self.rest = head, rest
        self.first, self.then = first, then


class Transducer:
    def __init__(self, vocabulary: Vocabulary):
        self.scores, self.add_prefix = vocabulary.scores, vocabulary.add_prefix
        self.side_by_side = {p[i : i + 2] for p in self.scores for i in range(len(p) - 1)}
        self.growing = {p[:i] for p in self.scores for i in range(1, len(p))}
        chars = {c for p in self.scores for c in p}
        if any(c not in self.scores for c in chars):
            raise ValueError("a character of a piece is no piece itself")
        # Where a mark follows something else, or a line ends, every vocabulary that keeps words apart has a boundary.
        words_apart = not any(x[1] == MARK != x[0] for x in self.side_by_side)
        lines_apart = "\n" not in chars
        self.segments = re.compile(f"{MARK}+[^{MARK}\\n]*|[^{MARK}\\n]+|\\n" if words_apart and lines_apart else r"(?s).+").findall
        self.beside: dict[tuple[str, str], bool] = {}
        self.whole: dict[str, bool] = {}
        self.memory: dict[str, int] = {}
        self._restart()

    def _restart(self) -> None:
        self.states: list[State] = []
        self.numbers: dict[State, int] = {}
        self.moves: list[dict[str, tuple[int, int]]] = []
        self.made = 0
        self.beside.clear()
        self.whole.clear()
        self.start = self._number(START)

    def _number(self, state: State) -> int:
        number = self.numbers.setdefault(state, len(self.states))
        if number == len(self.states):
            self.states.append(state)
            self.moves.append({})
        return number

    # -- compilation ------------------------------------------------------------------------------
    def merges(self, text: str) -> list[str]:
        """Pieces of a short text by merging the best-scored neighbours, leftmost first."""
        parts = list(text)
        while True:
            best = max(((self.scores[m], -i) for i in range(len(parts) - 1) if (m := parts[i] + parts[i + 1]) in self.scores), default=None)
            if best is None:
                return parts
            i = -best[1]
            parts[i : i + 2] = [parts[i] + parts[i + 1]]

    def _stays(self, left: str, right: str) -> bool:
        """Whether the merges give ``right`` as a piece of its own after ``left`` (or after nothing)."""
        if not left:
            if right not in self.whole:
                self.whole[right] = self.merges(right) == [right]
            return self.whole[right]
        if left[-1] + right[0] not in self.side_by_side:
            return self._stays("", right)
        known = self.beside.get((left, right))
        if known is None:
            known = self.beside[left, right] = self.merges(left + right) == [left, right]
        return known

    def _compile(self, state: int, char: str) -> tuple[int, int]:
        held = self.states[state]
        before = held[-1][1]
        if before and before[-1] + char not in self.side_by_side:
            held = START
        if char not in self.scores:
            move = (self.start, len(char.encode("utf-8", "surrogatepass")))
        else:
            grown = [(suffix + char, left, at) for suffix, left, at in held]
            piece, delta = next((s, at + 1) for s, left, at in grown if s in self.scores and self._stays(left, s))
            new = tuple((s, left, at - delta) for s, left, at in grown if s in self.growing) + (("", piece, 0),)
            move = (self._number(new), delta)
        self.moves[state][char] = move
        self.made += 1
        return move

    def run(self, state: State, text: str) -> tuple[State, int]:
        """Exit state and count after reading ``text`` from ``state``."""
        if self.made > COMPILED:
            self._restart()
        total, moves, at = 0, self.moves, self._number(state)
        for char in text:
            move = moves[at].get(char) or self._compile(at, char)
            at = move[0]
            total += move[1]
        return self.states[at], total

    # -- chunks -----------------------------------------------------------------------------------
    def chunk_map(self, chunk: str, before: str = "") -> StateMap:
        """Map of a chunk, with the row of the state that ``before``, the end of the text before it, leads to."""
        parts = self.segments(chunk)
        if len(parts) < 2:
            out = StateMap(chunk)
        else:
            state, total = self.run(START, parts[-1])
            out = StateMap(parts[0], (state, total + self._sum(parts[1:-1])))
        self.effect(out, self.run(START, before)[0])
        return out

    def effect(self, held: StateMap, entry: State) -> tuple[State, int]:
        """The row of an entry state, compiled if it is the first time that it is asked for."""
        row = held.rows.get(entry)
        if row is None:
            if held.first is not None:
                middle, count = self.effect(held.first, entry)
                state, more = self.effect(held.then, middle)
                row = state, count + more
            else:
                state, count = self.run(entry, held.head)
                row = (held.rest[0], count + held.rest[1]) if held.rest else (state, count)
            held.rows[entry] = row
        return row

    def compose(self, first: StateMap, then: StateMap) -> StateMap:
        """The map of one text after the other, with a row for each row of the first."""
        out = StateMap(first=first, then=then)
        for entry, (middle, count) in list(first.rows.items()):
            state, more = self.effect(then, middle)
            out.rows[entry] = state, count + more
        return out

    def prefix_scan(self, maps: list[StateMap]) -> list[StateMap]:
        """Map of every run of chunks from the first, in ceil(log2(n)) steps whose compositions are independent."""
        maps, reach = list(maps), 1
        while reach < len(maps):
            maps = maps[:reach] + [self.compose(a, b) for a, b in zip(maps, maps[reach:])]
            reach *= 2
        return maps

    def reduction(self, maps: list[StateMap]) -> StateMap:
        """Map of all chunks together, neighbours composed in ceil(log2(n)) steps."""
        while len(maps) > 1:
            maps = [self.compose(*maps[i : i + 2]) if i + 1 < len(maps) else maps[i] for i in range(0, len(maps), 2)]
        return maps[0]

    def apply(self, done: StateMap) -> int:
        return self.effect(done, START)[1]

    def _sum(self, parts: list[str]) -> int:
        """Counts of segments that each begin at the start state; short ones met before are remembered."""
        memory = self.memory
        try:
            return sum(map(memory.__getitem__, parts))
        except KeyError:
            pass
        total = 0
        for part in parts:
            n = memory.get(part)
            if n is None:
                n = self.run(START, part)[1]
                if len(part) <= SHORT:
                    memory[part] = n
            total += n
        return total

    def prepared(self, text: str) -> str:
        return (MARK if self.add_prefix else "") + text.replace(" ", MARK) if text else ""

    def maps(self, ready: str, size: int) -> list[StateMap]:
        return [self.chunk_map(ready[i : i + size], ready[max(0, i - OVERLAP) : i]) for i in range(0, len(ready), size)]

    def count(self, text: str | None) -> int:
        if not text:
            return 0
        if len(self.memory) > REMEMBER:
            self.memory.clear()
        ready = self.prepared(text)
        if len(ready) <= CHUNK:
            return self._sum(self.segments(ready))
        return self.apply(self.reduction(self.maps(ready, CHUNK)))

    def counts_by_chunk(self, text: str, size: int = CHUNK) -> list[int]:
        """Tokens of the text's prefixes that end with each chunk of ``size`` characters (of the prepared text)."""
        return [self.apply(m) for m in self.prefix_scan(self.maps(self.prepared(text), size))]


_MACHINES: dict[int, Transducer] = {}


def machine(vocabulary: Vocabulary) -> Transducer:
    """The worker's own transducer of a vocabulary, kept from task to task."""
    key = hash(frozenset(vocabulary.scores.items()))
    if key not in _MACHINES:
        _MACHINES.clear()
        _MACHINES[key] = Transducer(vocabulary)
    return _MACHINES[key]


def count_tokens(docs: DataFrame, model_path: str, limit: int = 4096) -> DataFrame:
    """UTF-8 bytes and tokens of every whole text, without begin, end or other special tokens.

    One narrow pass without a shuffle; the vocabulary (its size is the file's) is broadcast.
    """
    shared = docs.sparkSession.sparkContext.broadcast(read_model(model_path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = machine(shared.value)
        for batch in batches:
            found = batch.column("text").to_pylist()
            tokens = [counter.count(t) for t in found]
            sizes = [len(t.encode("utf-8", "surrogatepass")) if t else 0 for t in found]
            columns = [batch.column("doc_id").cast(pa.int64()), pa.array(sizes, pa.int64()), pa.array(tokens, pa.int64()), pa.array([n > limit for n in tokens], pa.bool_())]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return map_batches(texts(docs), run, SCHEMA, rows=500)
