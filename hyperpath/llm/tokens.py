"""Exact token counts by a deterministic transducer compiled from a byte-fallback BPE piece vocabulary.

The tokens of a text are the one sequence of pieces in which every two neighbours are stable: merging the two pieces' characters gives
the two pieces again (a merge across a boundary would show in that pair first). So the last token of a prefix is the one piece that
ends there and is stable after the last token of what is before it, and the count of every prefix follows from shorter ones.

A state of the transducer is what the next characters can depend on: the longest end of the text read that a piece may still
begin with and, for each place in it where a piece may have begun, the last token before that place and the tokens emitted
since (a bounded number, as pieces are). A transition on a character leads to the next state and is annotated with the change of the count;
it is compiled at the first visit. Where no piece holds the last character and the next one side by side, as before a space mark, the
next state depends on the character alone: a reset. A path between two resets is kept as one transition on the whole chunk.

A block of text is a map of states: what stands before its first reset is run from the state that the block is entered in,
and all after it has one exit state and one count. These maps compose associatively; the blocks of a long text are mapped
one by one and joined by the up-sweep of a prefix scan.

Defined results: null and empty texts have 0 tokens. Whole texts are counted, whatever their length; tables without rows give none;
rows of equal id are counted each. All tables of the transducer are bounded and compiled anew when they are full.
"""

from __future__ import annotations

import heapq
import re
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame

MARK = "▁"
BLOCK_CHARS = 1 << 16
#: Entries of the table of chunks, states, and pairs of pieces.
TABLE_LIMIT = 400_000


class State(dict):
    """character -> (next state, change of the count).

    window: the end of the text read that a piece may begin with. tokens[j], counts[j]: last token before place j of the window and the tokens up
    to there, less those up to now; None where no piece can begin or, as a token, where it can't matter.
    """

    __slots__ = ("counts", "model", "tokens", "window")

    def __init__(self, model: "PieceTransducer", window: str, tokens: tuple, counts: tuple) -> None:
        super().__init__()
        self.model, self.window, self.tokens, self.counts = model, window, tokens, counts

    def __missing__(self, char: str) -> tuple["State", int]:
        self[char] = out = self.model.compile(self, char)
        return out


class _Chunks(dict):
    """chunk -> tokens emitted on the path from reset to reset. Two generations bound the table: when the young one is
    full, it becomes the old one, and what is visited again moves back."""

    def __init__(self, model: "PieceTransducer") -> None:
        super().__init__()
        self.model, self.old = model, {}

    def __missing__(self, chunk: str) -> int:
        n = self.old.get(chunk) or self.model.run(self.model.root, chunk)[1]
        if len(chunk) <= 64:
            if len(self) >= TABLE_LIMIT:
                self.old = dict(self)
                self.clear()
            self[chunk] = n
        return n


@dataclass
class BlockMap:
    """head: what depends on the state of entry; then, if the block has a reset, its exit state and what it emits after the head."""

    head: str
    leaving: State | None = None
    emitted: int = 0


class PieceTransducer:
    """Built from (piece, score, kind) rows; kinds are those of the model format: 1 normal, 2 unknown, 3 control, 6 byte."""

    def __init__(self, pieces: list[tuple[str, float, int]], *, dummy_prefix: bool = True) -> None:
        self.rank = {p: -s for p, s, kind in pieces if kind in (1, 4)}
        self.dummy_prefix = dummy_prefix
        if any(MARK in p.lstrip(MARK) for p in self.rank):
            raise ValueError("a piece has a space mark after another character: spaces don't reset this vocabulary")
        self.begins = {p[:i] for p in self.rank for i in range(len(p) + 1)}
        self.beside = {p[i : i + 2] for p in self.rank for i in range(len(p) - 1)}
        newline = not any("\n" in x for x in self.beside)
        stop = r" \n" if newline else " "
        # A chunk: spaces with the run after them, a run at the start or after a newline, or a newline.
        self.chunks = re.compile(rf" +[^{stop}]*|[^{stop}]+" + (r"|\n" if newline else "")).findall
        self.states: dict[tuple, State] = {}
        self.pairs: dict[tuple[str, str], bool] = {}
        self.root = State(self, "", (None,), (0,))
        self.emitted = _Chunks(self)

    @classmethod
    def load(cls, path: str) -> "PieceTransducer":
        from sentencepiece import sentencepiece_model_pb2

        model = sentencepiece_model_pb2.ModelProto()
        with open(path, "rb") as f:
            model.ParseFromString(f.read())
        spec = model.normalizer_spec
        if model.trainer_spec.model_type != 2 or not model.trainer_spec.byte_fallback or spec.precompiled_charsmap or spec.remove_extra_whitespaces:
            raise ValueError("only BPE vocabularies with byte fallback and no normalisation compile to this transducer")
        return cls([(p.piece, p.score, p.type) for p in model.pieces], dummy_prefix=spec.add_dummy_prefix)

    # ---- compilation

    def merge(self, text: str) -> list[str]:
        """Pieces of a text by the vocabulary's own rule: the best-ranked adjacent pair merges first, the leftmost of equals."""
        part, rank = list(text), self.rank
        left, right = list(range(-1, len(part) - 1)), list(range(1, len(part) + 1))
        queue = [(rank[a + b], i, a, b) for i, (a, b) in enumerate(zip(part, part[1:], strict=False)) if a + b in rank]
        heapq.heapify(queue)

        def offer(i: int, j: int) -> None:
            if i >= 0 and j < len(part) and part[i] + part[j] in rank:
                heapq.heappush(queue, (rank[part[i] + part[j]], i, part[i], part[j]))

        while queue:
            _, i, a, b = heapq.heappop(queue)
            j = right[i] if part[i] else len(part)
            if j >= len(part) or part[i] != a or part[j] != b:
                continue
            part[i], part[j] = a + b, ""
            right[i] = right[j]
            if right[i] < len(part):
                left[right[i]] = i
            offer(left[i], i)
            offer(i, right[i])
        return [p for p in part if p]

    def stable(self, before: str | None, piece: str) -> bool:
        """Whether piece can follow the token before it."""
        key = before or "", piece
        found = self.pairs.get(key)
        if found is None:
            if len(self.pairs) >= TABLE_LIMIT:
                self.pairs.clear()
            found = self.pairs[key] = self.merge(key[0] + piece) == ([before, piece] if before else [piece])
        return found

    def compile(self, state: State, char: str) -> tuple[State, int]:
        """The state after char, and by how much the count changes."""
        grown = state.window + char
        tokens = list(state.tokens)
        if tokens[-1] and tokens[-1][-1] + char not in self.beside:
            tokens[-1] = None  # no piece joins what is before with char
        for j, n in enumerate(state.counts):
            piece = grown[j:]
            known = piece in self.rank
            if n is not None and (known or len(piece) == 1) and self.stable(tokens[j], piece):
                # A character that is no piece falls back to its bytes.
                change = n + (1 if known else len(char.encode("utf-8", "surrogatepass")))
                break
        else:
            raise AssertionError(f"no token ends after {grown!r}")
        tokens.append(piece)
        counts = [None if n is None else n - change for n in state.counts] + [0]
        begin = next(j for j in range(len(grown) + 1) if grown[j:] in self.begins)
        live = [j for j in range(begin, len(grown) + 1)]
        useful = [grown[j:] in self.begins and counts[j] is not None for j in live]
        key = grown[begin:], tuple(tokens[j] if u else None for j, u in zip(live, useful, strict=True)), tuple(counts[j] if u else None for j, u in zip(live, useful, strict=True))
        found = self.states.get(key)
        if found is None:
            if len(self.states) >= TABLE_LIMIT:
                self.states.clear()
                self.root.clear()
            found = self.states[key] = State(self, *key)
        return found, change

    # ---- counting

    def run(self, state: State, text: str) -> tuple[State, int]:
        """The state after a text that is read from a state, and the tokens emitted."""
        n = 0
        for char in text.replace(" ", MARK):
            state, change = state[char]
            n += change
        return state, n

    def block_map(self, block: str) -> BlockMap:
        found = self.chunks(block)
        if len(found) < 2:
            return BlockMap(block)
        leaving, n = self.run(self.root, found[-1])
        return BlockMap(found[0], leaving, sum(map(self.emitted.__getitem__, found[1:-1])) + n)

    def compose(self, x: BlockMap, y: BlockMap) -> BlockMap:
        """The map of two adjacent blocks."""
        if x.leaving is None:
            return BlockMap(x.head + y.head, y.leaving, y.emitted)
        leaving, n = self.run(x.leaving, y.head)
        return BlockMap(x.head, leaving if y.leaving is None else y.leaving, x.emitted + n + y.emitted)

    def scan(self, maps: list[BlockMap]) -> BlockMap:
        """Join the maps of all blocks in a balanced tree (the up-sweep of a prefix scan)."""
        while len(maps) > 1:
            maps = [self.compose(*maps[i : i + 2]) if i + 1 < len(maps) else maps[i] for i in range(0, len(maps), 2)]
        return maps[0]

    def count(self, text: str, block: int = BLOCK_CHARS) -> int:
        if not text:
            return 0
        if self.dummy_prefix:
            text = " " + text
        text = text.replace(MARK, " ")  # the model takes a written mark for a space
        if len(text) <= block:
            return sum(map(self.emitted.__getitem__, self.chunks(text)))
        whole = self.scan([self.block_map(text[i : i + block]) for i in range(0, len(text), block)])
        return self.run(self.root, whole.head)[1] + whole.emitted


_loaded: dict[str, PieceTransducer] = {}


def transducer(path: str) -> PieceTransducer:
    """One per worker process; its table outlives the task."""
    if path not in _loaded:
        _loaded[path] = PieceTransducer.load(path)
    return _loaded[path]


def count_tokens(docs: DataFrame, model_path: str, *, id_col: str = "doc_id", text_col: str = "text", limit: int = 4096) -> DataFrame:
    """id, n_bytes (UTF-8), n_tokens, over_limit per document; map-only. model_path must exist on every worker."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = transducer(model_path)
        for batch in batches:
            texts = batch.column(1)
            sizes = [len(x or b"") for x in texts.cast(pa.binary()).to_pylist()]
            n = [model.count(x or "") for x in texts.to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(sizes, pa.int64()), pa.array(n, pa.int64()), pa.array([x > limit for x in n], pa.bool_())],
                names=[id_col, "n_bytes", "n_tokens", "over_limit"],
            )

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, n_bytes long, n_tokens long, over_limit boolean")
