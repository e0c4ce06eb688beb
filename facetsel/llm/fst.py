"""Token counts by a finite-state transducer compiled from a BPE vocabulary.

A sequence of pieces is the BPE encoding of its text exactly if every two neighbours are the encoding of theirs, so the
last piece of each prefix is settled by the last pieces of few earlier prefixes. A state of the transducer holds those:
for every start from which a longer piece could still grow, the characters since, the piece that ends there and how many
tokens it lacks to the present count. Reading a character gives the next state and the number of tokens emitted, which
may be negative where a longer piece replaces shorter ones. States and transitions are made when first met and kept;
when there are too many of either they are dropped and made again, so memory is bounded (some 250 MB a worker, whatever
the texts hold) and counts stay exact.

Between two characters that no piece holds side by side the transducer forgets its past: there it synchronises. A chunk
of text is a map from the state before it to the state after it and a count: its characters up to the first synchronising
point, a count from there on, and a fixed state at its end. Such maps compose associatively, which is what lets long
texts be cut anywhere, their chunks be read by different tasks, and the maps be joined pairwise in a tree; and what lets
chunks between synchronising points be counted once and looked up again."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass
from functools import lru_cache

SPACE = "▁"


@dataclass(frozen=True)
class ChunkMap:
    """Reads head from any state before it; if closed, then emits count and ends in state whatever came before. A state is
    told by what it holds, so that maps go from one worker to another."""

    head: str
    closed: bool = False
    count: int = 0
    state: tuple = ()


class CountTransducer:
    """scores: piece -> score, of ordinary pieces only; any other character counts as its UTF-8 bytes."""

    def __init__(self, scores: dict[str, float], most_states: int = 150_000, most_steps: int = 400_000):
        self.scores, self.most_states, self.most_steps = scores, most_states, most_steps
        self.prefixes = {p[:i] for p in scores for i in range(1, len(p))}
        self.joined = {p[i : i + 2] for p in scores for i in range(len(p) - 1)}
        self._whole = lru_cache(50_000)(self._whole)
        self.clear()

    def clear(self) -> None:
        self.ids: dict[tuple, int] = {}
        self.states: list[tuple] = []
        self.next: list[dict[str, tuple[int, int]]] = []
        self.steps = 0
        self.start = self._id((("", None, 0),))

    def _id(self, state: tuple) -> int:
        if (n := self.ids.get(state)) is None:
            n = self.ids[state] = len(self.states)
            self.states.append(state)
            self.next.append({})
        return n

    def encode(self, text: str) -> list[str]:
        """Plain BPE: merge the best-scored neighbours, leftmost first, until none is a piece."""
        parts = list(text)
        while True:
            best, at = None, -1
            for i in range(len(parts) - 1):
                score = self.scores.get(parts[i] + parts[i + 1])
                if score is not None and (best is None or score > best):
                    best, at = score, i
            if at < 0:
                return parts
            parts[at : at + 2] = [parts[at] + parts[at + 1]]

    def _whole(self, before: str | None, piece: str) -> bool:
        """Whether piece stays as it is after the piece before it (None: after a synchronising point)."""
        return self.encode((before or "") + piece) == ([before] if before else []) + [piece]

    def synchronises(self, a: str, b: str) -> bool:
        return a + b not in self.joined

    def step(self, state: int, ch: str) -> tuple[int, int]:
        """The transition, made if need be; emptying the tables may renumber states, so callers go by key()."""
        live = self.states[state]
        kept, last = [], None
        for since, piece, lack in live:
            if not since and piece and self.synchronises(piece[-1], ch):
                piece = None
            grown = since + ch
            if (grown in self.scores or len(grown) == 1) and self._whole(piece, grown):
                last = (grown, 1 - lack if grown in self.scores else len(ch.encode()) - lack)
            if grown in self.prefixes:
                kept.append((grown, piece, lack))
        piece, emitted = last
        after = (*((s, p, k + emitted) for s, p, k in kept), ("", piece if piece in self.scores else None, 0))
        out = self.next[state][ch] = (self._id(after), emitted)
        self.steps += 1
        return out

    def walk(self, state: int, text: str) -> tuple[int, int]:
        tables, n = self.next, 0
        for ch in text:
            try:
                state, k = tables[state][ch]
            except KeyError:
                if len(self.states) > self.most_states or self.steps > self.most_steps:
                    state = self.reset(state)
                    tables = self.next
                state, k = self.step(state, ch)
            n += k
        return state, n

    def reset(self, state: int) -> int:
        here = self.states[state]
        self.clear()
        return self._id(here)

    def chunk(self, text: str) -> ChunkMap:
        at = next((i for i in range(1, len(text)) if self.synchronises(text[i - 1], text[i])), None)
        if at is None:
            return ChunkMap(text)
        state, n = self.walk(self.start, text[at:])
        return ChunkMap(text[:at], True, n, self.states[state])

    def compose(self, first: ChunkMap, second: ChunkMap) -> ChunkMap:
        if not first.closed:
            joint = self.chunk(first.head + second.head)
            if not second.closed:
                return joint
            if not joint.closed:
                return ChunkMap(joint.head, True, second.count, second.state)
            return ChunkMap(joint.head, True, joint.count + second.count, second.state)
        state, n = self.walk(self._id(first.state), second.head)
        if second.closed:
            return ChunkMap(first.head, True, first.count + n + second.count, second.state)
        return ChunkMap(first.head, True, first.count + n, self.states[state])

    def scanned(self, maps: list[ChunkMap]) -> ChunkMap:
        """The map of all, in order: neighbours are joined level by level, as a parallel scan has it."""
        while len(maps) > 1:
            pairs = [self.compose(a, b) for a, b in zip(maps[::2], maps[1::2], strict=False)]
            maps = pairs + maps[len(maps) & ~1 :]
        return maps[0]

    def total(self, whole: ChunkMap) -> int:
        return self.walk(self.start, whole.head)[1] + whole.count

    def count(self, text: str, chunk: int = 1 << 16) -> int:
        """The tokens of a text of any length."""
        if len(text) <= chunk:
            return self.walk(self.start, text)[1]
        return self.total(self.scanned([self.chunk(text[i : i + chunk]) for i in range(0, len(text), chunk)]))


class WordCounts(dict):
    """Chunks between white space, each after one space, with their counts. Of two generations of at most so many words
    the older one is dropped when the newer is full; words that are met again meanwhile move on."""

    def __init__(self, machine: CountTransducer, most: int = 150_000, longest: int = 40):
        self.machine, self.most, self.longest, self.older = machine, most, longest, {}

    def __missing__(self, word: str) -> int:
        n = self.older.get(word)
        if n is None:
            n = self.machine.count(SPACE + word)
        if len(word) <= self.longest:
            if len(self) >= self.most:
                self.older = dict(self)
                self.clear()
            self[word] = n
        return n


class PieceCounter:
    """Token counts as the sentencepiece library gives them for a BPE model with identity normalisation."""

    def __init__(self, model_file: str):
        from sentencepiece import sentencepiece_model_pb2

        model = sentencepiece_model_pb2.ModelProto()
        with open(model_file, "rb") as f:
            model.ParseFromString(f.read())
        rule = model.normalizer_spec
        if model.trainer_spec.model_type != 2 or rule.precompiled_charsmap or rule.remove_extra_whitespaces or not (rule.add_dummy_prefix and rule.escape_whitespaces and model.trainer_spec.byte_fallback):
            raise ValueError("only BPE models with byte fallback and identity normalisation are compiled")
        if any(p.type == 4 for p in model.pieces):
            raise ValueError("user-defined pieces are not compiled")
        scores = {p.piece: p.score for p in model.pieces if p.type == 1}
        if any(p[i] == SPACE != p[i - 1] for p in scores for i in range(1, len(p))):
            raise ValueError("pieces must not go over the start of a word")
        self.machine = CountTransducer(scores)
        self.words = WordCounts(self.machine)

    def __call__(self, text: str) -> int:
        """Words start at synchronising points, so their maps compose by addition; where spaces stand together, the
        transducer reads the run of text between them as it is."""
        if not text:
            return 0
        text = text.replace(" ", SPACE)
        if text[0] != SPACE and SPACE + SPACE not in text and text[-1] != SPACE:
            return sum(map(self.words.__getitem__, text.split(SPACE)))
        n, run = 0, ""
        for part in (SPACE + text)[1:].split(SPACE):  # run: spaces not yet given to a word
            if part:
                n += self.words[part] if not run else self.machine.count(run + SPACE + part)
                run = ""
            else:
                run += SPACE
        return n + (self.machine.count(run) if run else 0)

    def chunk(self, text: str, first: bool) -> ChunkMap:
        """The map of one of the chunks that a text is cut into anywhere. Between its first and last words, words are
        looked up; the walk from word to word is a walk from one synchronising point to the next."""
        text = (SPACE if first else "") + text.replace(" ", SPACE)
        lo = text.find(SPACE, 1)
        hi = text.rfind(SPACE)
        if lo < 0 or hi <= lo or not self.machine.synchronises(text[lo - 1], SPACE) or SPACE + SPACE in text:
            return self.machine.chunk(text)
        tail, n = self.machine.walk(self.machine.start, text[hi:])
        return ChunkMap(text[:lo], True, sum(map(self.words.__getitem__, text[lo + 1 : hi].split(SPACE))) + n, self.machine.states[tail])

    def joined(self, maps: list[ChunkMap]) -> int:
        return self.machine.total(self.machine.scanned(maps)) if maps else 0

    def all(self, texts: Iterable[str | None]) -> list[int]:
        return [self(t) if t else 0 for t in texts]


@lru_cache(2)
def piece_counter(model_file: str) -> PieceCounter:
    return PieceCounter(model_file)
