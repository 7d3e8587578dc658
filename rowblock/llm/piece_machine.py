"""A piece vocabulary with merge ranks, compiled lazily into a finite-state transducer.

The encoding of a text by best-first merges is the one chain of pieces in which every two neighbours
stay as they are when their joint text is encoded alone. So the last piece of each prefix of a text is
decided by the last pieces of shorter prefixes, and only those from which a piece
may still grow matter. A state holds exactly these: how far back each is, its last piece, and its
number of pieces relative to the newest prefix. There are finitely many; a state, and a
transition, is compiled when first met. A transition carries the change of the number of pieces, and
the newest prefix's last piece for tracing ids.

No piece of the vocabulary has a space mark after another character. So wherever a space mark follows another
character the machine stands in its start state again, and segments between are independent.
"""

from __future__ import annotations

import re
from functools import lru_cache
from itertools import chain

MARK = "▁"
MOST_STATES = 300_000
LOOK = 2048  # characters between two looks at the number of states
CHUNK = 8192
MEMO = 400_000


class Vocabulary:
    """Pieces of a model file: those that merges can make, the ids of bytes, and the text of every id."""

    def __init__(self, pieces: dict[str, tuple[int, float]], byte_ids: list[int], spelled: list[bytes]) -> None:
        self.pieces, self.byte_ids, self.spelled = pieces, byte_ids, spelled
        self.longest = max(map(len, pieces), default=1)
        self.starts = {p[:k] for p in pieces for k in range(1, len(p))}
        if any(re.search(f"[^{MARK}]{MARK}", p) for p in pieces):
            raise ValueError("pieces that reach over a space are not supported")
        self.alone = lru_cache(maxsize=1 << 16)(self._alone)
        self.neighbours = lru_cache(maxsize=1 << 19)(self._neighbours)

    @classmethod
    def load(cls, path: str) -> Vocabulary:
        from sentencepiece import sentencepiece_model_pb2

        model = sentencepiece_model_pb2.ModelProto()
        with open(path, "rb") as file:
            model.ParseFromString(file.read())
        norm = model.normalizer_spec
        if model.trainer_spec.model_type != 2 or not model.trainer_spec.byte_fallback or norm.precompiled_charsmap or norm.remove_extra_whitespaces or not norm.add_dummy_prefix or not norm.escape_whitespaces:
            raise ValueError("only merge models with byte fallback and plain normalisation are supported")
        pieces = {p.piece: (i, p.score) for i, p in enumerate(model.pieces) if p.type == 1}
        spelled = [bytes([int(p.piece[3:5], 16)]) if p.type == 6 else b"" if p.type in (2, 3) else p.piece.replace(MARK, " ").encode() for p in model.pieces]
        byte_ids = [0] * 256
        for i, p in enumerate(model.pieces):
            if p.type == 6:
                byte_ids[int(p.piece[3:5], 16)] = i
        return cls(pieces, byte_ids, spelled)

    def merged(self, text: str) -> list[str]:
        """Best-first merges of a short text: the highest score first, of equal ones the leftmost."""
        parts = list(text)
        while len(parts) > 1:
            best, at = None, -1
            for k in range(len(parts) - 1):
                found = self.pieces.get(parts[k] + parts[k + 1])
                if found and (best is None or found[1] > best):
                    best, at = found[1], k
            if best is None:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts

    def _alone(self, piece: str) -> bool:
        return self.merged(piece) == [piece]

    def _neighbours(self, left: str, right: str) -> bool:
        return self.merged(left + right) == [left, right]


class State(dict):
    """Transitions by character: (next state, change of the count, id of the last piece or -1, its length)."""

    __slots__ = ("machine", "tail", "alive")
    __hash__ = object.__hash__

    def __eq__(self, other: object) -> bool:
        return self is other

    def __ne__(self, other: object) -> bool:
        return self is not other

    def __repr__(self) -> str:
        return f"State({self.tail!r}, {self.alive!r})"

    def __init__(self, machine: Machine, tail: str, alive: tuple) -> None:
        super().__init__()
        self.machine, self.tail, self.alive = machine, tail, alive

    def __missing__(self, char: str) -> tuple:
        found = self[char] = self.machine.step(self, char)
        return found


class Machine:
    """The transducer over a vocabulary, with counts and ids of whole texts."""

    def __init__(self, vocabulary: Vocabulary) -> None:
        self.v = vocabulary
        self.reset()

    def reset(self) -> None:
        self.states: dict[tuple, State] = {}
        self.start = self.state("", ((0, "", 0),))
        self.counts = _Memo(lambda segment: self.count_segment(MARK + segment))
        self.ids = _Memo(lambda segment: tuple(self.ids_of_segment(MARK + segment)))

    def state(self, tail: str, alive: tuple) -> State:
        key = (tail, alive)
        found = self.states.get(key)
        if found is None:
            found = self.states[key] = State(self, tail, alive)
        return found

    def step(self, state: State, char: str) -> tuple:
        v = self.v
        if char not in v.pieces:
            return self.start, len(char.encode("utf-8", "surrogatepass")), -1, 1
        before = state.alive[-1][1]
        if char == MARK and before and before[-1] != MARK:
            return self.start[char]  # nothing reaches over the border
        text = state.tail + char
        for back, last, count in state.alive:  # farthest first
            piece = text[len(text) - back - 1 :]
            if piece in v.pieces and v.alone(piece) and (not last or v.neighbours(last, piece)):
                break
        else:
            raise ValueError(f"no last piece for {text!r}")
        delta = count + 1
        alive = tuple((b + 1, p, c - delta) for b, p, c in state.alive if text[len(text) - b - 1 :] in v.starts) + ((0, piece, 0),)
        tail = text[len(text) - alive[0][0] :] if alive[0][0] else ""
        return self.state(tail, alive), delta, v.pieces[piece][0], len(piece)

    def bounded(self, state: State) -> State:
        """The same state, in a new table where the old one has too many; states that nobody holds are given back.

        Between two looks a run adds at most LOOK states, or two for each character of a chunk's head.
        """
        if len(self.states) <= MOST_STATES:
            return state
        self.reset()
        return self.state(state.tail, state.alive)

    def run(self, state: State, given: str) -> tuple[State, int]:
        """The state after an escaped text, and how many pieces it adds."""
        total = 0
        for at in range(0, len(given), LOOK):
            state = self.bounded(state)
            for char in given[at : at + LOOK]:
                state, delta, _, _ = state[char]
                total += delta
        return state, total

    def count_segment(self, segment: str) -> int:
        """Pieces of an escaped segment, that is one that begins where the machine starts."""
        return self.run(self.start, segment)[1]

    def ids_of_segment(self, segment: str) -> list[int]:
        encoder = StreamingEncoder(self)
        return [*encoder.feed(segment), *encoder.finish()]

    def count(self, text: str, chunk: int = CHUNK) -> int:
        """Pieces of a text: the state maps of its chunks, each made without the others, composed by a tree and applied to the start."""
        if not text:
            return 0
        given = " " + text.replace(MARK, " ")
        return scan([ChunkMap(self, given[i : i + chunk]) for i in range(0, len(given), chunk)])(self.start)[1]

    def count_plain(self, given: str) -> int:
        """Pieces of a text with spaces for marks that begins at a segment's start."""
        if not given:
            return 0
        if given[0] == " " and given[-1] != " " and "  " not in given:
            return sum(map(self.counts.__getitem__, given[1:].split(" ")))
        return sum(self.counts[s[1:].replace(" ", MARK)] if s[0] == " " else self.count_segment(s) for s in segments(given))

    def encode(self, text: str) -> list[int]:
        if not text:
            return []
        given = " " + text.replace(MARK, " ")
        if given[-1] != " " and "  " not in given:
            return list(chain.from_iterable(map(self.ids.__getitem__, given[1:].split(" "))))
        return list(chain.from_iterable(self.ids[s[1:].replace(" ", MARK)] if s[0] == " " else self.ids_of_segment(s) for s in segments(given)))

    def decode(self, ids: list[int]) -> str:
        """The text of ids; bytes that are no UTF-8 become the replacement character, and the first space is dropped."""
        text = b"".join(map(self.v.spelled.__getitem__, ids)).decode("utf-8", "replace")
        return text[1:] if text.startswith(" ") else text


class ChunkMap:
    """From each state before a chunk to the state after it and the number of pieces in between.

    From the first segment that starts within the chunk on, nothing depends on the state before; the pieces from there are counted
    once, without knowing it. The part before, the head, is run once from the start state; from another state it is run
    until both runs stand in one state, which takes no longer than the pieces reach, and what is left is known.
    """

    def __init__(self, machine: Machine, given: str) -> None:
        self.machine = machine
        inner = re.search("(?<=[^ ]) ", given)
        self.head = (given[: inner.start()] if inner else given).replace(" ", MARK)
        self.rest: tuple[State, int] | None = None
        if inner:
            last = given.rindex(" ")
            while given[last - 1] == " ":  # the last segment starts at the first of its spaces
                last -= 1
            closed = machine.count_plain(given[inner.start() : last])
            state, n = machine.run(machine.start, given[last:].replace(" ", MARK))
            self.rest = state, closed + n
        self.path: list[tuple[State, int]] | None = None

    def __call__(self, state: State) -> tuple[State, int]:
        after, n = self.through_head(state)
        return (self.rest[0], n + self.rest[1]) if self.rest else (after, n)

    def through_head(self, state: State) -> tuple[State, int]:
        machine = self.machine
        if state is machine.start or not self.head:
            return machine.run(state, self.head)
        if self.path is None:
            self.path, now, total = [], machine.start, 0
            for char in self.head:
                now, delta, _, _ = now[char]
                total += delta
                self.path.append((now, total))
        total = 0
        for char, (met, n) in zip(self.head, self.path, strict=True):
            state, delta, _, _ = state[char]
            total += delta
            if state is met:
                return self.path[-1][0], total + self.path[-1][1] - n
        return state, total


def scan(maps: list):
    """The composition of maps in their order, as a tree: every pair on a level is independent of the others."""
    while len(maps) > 1:
        maps = [_after(*maps[i : i + 2]) if i + 1 < len(maps) else maps[i] for i in range(0, len(maps), 2)]
    return maps[0]


def _after(first, second):
    def both(state: State) -> tuple[State, int]:
        middle, m = first(state)
        end, n = second(middle)
        return end, m + n

    return both


class _Memo(dict):
    """Results of segments, at most MEMO of them, and only of those that are short."""

    def __init__(self, make) -> None:
        super().__init__()
        self.make = make

    def __missing__(self, segment: str):
        found = self.make(segment)
        if len(segment) <= 48:
            if len(self) >= MEMO:
                self.clear()
            self[segment] = found
        return found


def segments(given: str) -> list[str]:
    return re.findall(" *[^ ]+| +", given)


class StreamingEncoder:
    """Viterbi over a stream of characters.

    Each prefix has one valid last piece, its backpointer. What is kept is the backpointers since the
    last committed boundary. Ids are committed when the paths of all prefixes from which a piece
    may still grow meet in one boundary.
    """

    def __init__(self, machine: Machine) -> None:
        self.machine, self.state = machine, machine.start
        self.back: list[tuple[int, int]] = []
        self.chars: list[str] = []

    def feed(self, text: str) -> list[int]:
        out: list[int] = []
        for k, char in enumerate(text):
            if k % LOOK == 0:
                self.state = self.machine.bounded(self.state)
            self.state, _, piece, length = self.state[char]
            self.back.append((piece, length))
            self.chars.append(char)
            if len(self.state.alive) == 1 or len(self.back) >= 4 * self.machine.v.longest:
                out += self._commit(self._meeting())
        return out

    def finish(self) -> list[int]:
        return self._commit(len(self.back))

    def _meeting(self) -> int:
        """The last boundary on the paths of all prefixes that are alive, from the start of the window."""
        ends = {len(self.back) - back for back, _, _ in self.state.alive}
        while len(ends) > 1:
            last = max(ends)
            if last <= 0:
                return 0
            ends.remove(last)
            ends.add(last - self.back[last - 1][1])
        return max(0, ends.pop())

    def _commit(self, end: int) -> list[int]:
        out: list[int] = []
        at = end
        while at > 0:
            piece, length = self.back[at - 1]
            out += [piece] if piece >= 0 else [self.machine.v.byte_ids[b] for b in reversed(self.chars[at - 1].encode("utf-8", "surrogatepass"))]
            at -= length
        del self.back[:end], self.chars[:end]
        return out[::-1]


@lru_cache(maxsize=2)
def machine(path: str) -> Machine:
    """One machine for a model file in each process."""
    return Machine(Vocabulary.load(path))
