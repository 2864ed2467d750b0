"""Segmentation of texts into the pieces of a public SentencePiece vocabulary, n best ways.

The lattice of a text has a node between any two characters and an edge for every
piece that matches there; a character without a piece is spelled by its bytes.  A
forward Viterbi pass gives every node the score of the best way to it.  A search from
the end backward takes those scores as heuristics: being exact, they make A* pop
complete segmentations in order of score, so the first n are the n best.

A space opens every piece that holds one, hence no piece crosses from one word to the
next, and the best ways of a text combine those of its words.  A batch therefore runs
the forward pass (best and second best score) over its distinct words at once, and the
backward search only in the few words where a text's best alternatives can lie.  Each of
the n best ways comes back with its ids: the best ids of the text, with those of the
words in which the way departs put in their place.

Scores.  Vocabularies of unigram models carry log probabilities (``score="model"``).
Byte-pair vocabularies carry merge ranks, which do not add up along a path;
``score="zipf"`` takes the log probability of a piece of that rank under Zipf's law.
"""

from __future__ import annotations

import hashlib
import heapq
import itertools
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .frames import add_columns
from .textkernel import mix64

SPACE = "▁"
#: Stands for a literal SPACE character of a text, which is spelled by bytes.
_LITERAL = "\U0010fffd"
_MOST = 48  # words up to this many characters go through the vectorised pass
_BASE = np.uint64(0x9E3779B97F4A7C15)
_BUCKET_BITS = 18


@dataclass(frozen=True)
class Segmented:
    """Best ways of many words: scores, and their ids in one body."""

    best: np.ndarray
    second: np.ndarray
    body: np.ndarray
    starts: np.ndarray
    sizes: np.ndarray


@dataclass(frozen=True)
class Pieces:
    """Pieces with scores by id; ids of the 256 byte pieces."""

    ids: dict[str, int]
    scores: dict[str, float]
    texts: list[str]
    byte_ids: list[int]
    byte_score: float
    longest: int
    table: tuple[np.ndarray, ...] = field(repr=False, default=())

    # --- one text -----------------------------------------------------------

    def _edges(self, text: str, end: int) -> Iterator[tuple[int, float, tuple[int, ...]]]:
        """(start, score, ids) of the pieces that end at a node."""
        for start in range(max(0, end - self.longest), end):
            piece = text[start:end]
            if piece in self.ids:
                yield start, self.scores[piece], (self.ids[piece],)
            elif end - start == 1:
                raw = (SPACE if piece == _LITERAL else piece).encode("utf-8", "surrogatepass")
                yield start, self.byte_score * len(raw), tuple(self.byte_ids[b] for b in raw)

    def forward(self, text: str) -> list[float]:
        """Score of the best way to every node."""
        best = [0.0] + [-np.inf] * len(text)
        for end in range(1, len(text) + 1):
            for start, score, _ in self._edges(text, end):
                best[end] = max(best[end], best[start] + score)
        return best

    def nbest(self, text: str, n: int) -> list[tuple[float, tuple[int, ...]]]:
        """The n best segmentations (score, ids) of a marked text, best first.

        Ways of one score come in the order of the search, which goes on with the entry
        nearest to the start; it is the same for the same text.  A node is expanded n
        times at most, and entries share the ids behind them as links, so memory follows
        the length of the text.
        """
        ahead = self.forward(text)
        queue: list[tuple] = [(-ahead[-1], len(text), 0, 0.0, None)]  # negated score of the whole way, node, order, score behind, ids behind
        visits = [0] * (len(text) + 1)
        found: list[tuple[float, tuple[int, ...]]] = []
        made = 0
        while queue and len(found) < n:
            _, node, _, behind, link = heapq.heappop(queue)
            if node == 0:
                ids: list[int] = []
                while link is not None:
                    own, link = link
                    ids += own
                found.append((behind, tuple(ids)))
                continue
            visits[node] += 1
            if visits[node] > n:
                continue
            for start, score, own in self._edges(text, node):
                made += 1
                heapq.heappush(queue, (-round(ahead[start] + score + behind, 9), start, made, score + behind, (own, link)))
        return found

    # --- many words ---------------------------------------------------------

    def _lookup(self, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(score, id) of pieces by hash; -inf and -1 where there is none."""
        keys, scores, ids, first = self.table
        codes = mix64(codes)
        bucket = (codes >> np.uint64(64 - _BUCKET_BITS)).astype(np.int64)
        at, stop = first[bucket], first[bucket + 1]
        score, piece = np.full(len(codes), -np.inf), np.full(len(codes), -1, dtype=np.int64)
        live = np.flatnonzero(at < stop)
        while len(live):
            hit = keys[at[live]] == codes[live]
            found = live[hit]
            score[found], piece[found] = scores[at[found]], ids[at[found]]
            live = live[~hit]
            at[live] += 1
            live = live[at[live] < stop[live]]
        return score, piece

    def many(self, words: list[str]) -> Segmented:
        """Best score, second best score (-inf if there is one way only) and best ids of each word."""
        n = len(words)
        best, second = np.zeros(n), np.full(n, -np.inf)
        parts: list[np.ndarray | None] = [None] * n
        sizes = np.zeros(n, dtype=np.int64)
        lengths = np.fromiter(map(len, words), np.int64, n)
        order = np.argsort(lengths, kind="stable")
        flat: list[np.ndarray] = []
        placed: list[int] = []
        for members in np.split(order, np.flatnonzero(np.diff(lengths[order])) + 1) if n else []:
            length = int(lengths[members[0]])
            if length > _MOST:
                for i in members.tolist():
                    two = self.nbest(words[i], 2)
                    best[i], second[i] = two[0][0], two[1][0] if len(two) > 1 else -np.inf
                    parts[i] = np.array(two[0][1], dtype=np.int32)
            else:
                for low in range(0, len(members), 8_000):
                    part = members[low : low + 8_000]
                    best[part], second[part], ids, count, odd = self._same_length([words[i] for i in part.tolist()], length)
                    for k in odd.tolist():  # characters that several bytes spell
                        i = int(part[k])
                        parts[i] = np.array(self.nbest(words[i], 1)[0][1], dtype=np.int32)
                    plain = np.ones(len(part), dtype=bool)
                    plain[odd] = False
                    sizes[part] = count
                    flat.append(ids[np.repeat(plain, count)])
                    placed += part[plain].tolist()
        body = np.concatenate([*flat, np.zeros(0, np.int32)])
        ends = np.cumsum(sizes[placed]) if placed else np.zeros(0, np.int64)
        starts = np.zeros(n, dtype=np.int64)
        starts[placed] = ends - sizes[placed] if placed else 0
        for i, own in enumerate(parts):
            if own is not None:
                starts[i], sizes[i] = len(body), len(own)
                body = np.concatenate([body, own])
        return Segmented(best, second, body, starts, sizes)

    def _same_length(self, words: list[str], length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(best, second, ids of all words in a row, ids by word, words with characters of several bytes)."""
        n = len(words)
        codes = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), dtype=np.uint32).reshape(n, length).T.astype(np.uint64)
        prefix = np.zeros((length + 1, n), dtype=np.uint64)
        power = [pow(int(_BASE), k, 2**64) for k in range(length + 1)]
        for k in range(length):
            prefix[k + 1] = prefix[k] * _BASE + codes[k] + np.uint64(1)
        spelled = np.where(codes < 0x80, 1, np.where(codes < 0x800, 2, np.where(codes < 0x10000, 3, 4)))
        spelled[codes == ord(_LITERAL)] = 3
        first = np.full((length + 1, n), -np.inf)
        second = np.full((length + 1, n), -np.inf)
        back = np.zeros((length + 1, n), dtype=np.int64)
        used = np.zeros((length + 1, n), dtype=np.int64)
        first[0] = 0.0
        for end in range(1, length + 1):
            for start in range(max(0, end - self.longest), end):
                score, piece = self._lookup(prefix[end] - prefix[start] * np.uint64(power[end - start]))
                if end - start == 1:
                    score = np.where(piece < 0, self.byte_score * spelled[start], score)
                elif not np.isfinite(score).any():
                    continue
                a, b = first[start] + score, second[start] + score
                better = a > first[end]
                second[end] = np.maximum(np.minimum(first[end], a), np.maximum(second[end], b))
                first[end] = np.where(better, a, first[end])
                back[end] = np.where(better, start, back[end])
                used[end] = np.where(better, piece, used[end])
        node, rows = np.full(n, length), np.arange(n)
        taken = np.full((length, n), -2, dtype=np.int64)  # from the end backward
        odd = np.zeros(n, dtype=bool)
        for step in range(length):
            piece, start = used[node, rows], back[node, rows]
            spell = (piece < 0) & (node > 0)
            letter = codes[np.minimum(start, length - 1), rows]
            odd |= spell & (letter >= 0x80)
            piece = np.where(spell, self.byte_ids[0] + np.minimum(letter, np.uint64(127)).astype(np.int64), piece)
            taken[step] = np.where(node > 0, piece, -2)
            node = np.where(node > 0, start, 0)
        ids = taken[::-1].T  # by word, in order; -2 where a word has fewer pieces
        real = ids != -2
        return first[length], second[length], ids[real].astype(np.int32), real.sum(axis=1), np.flatnonzero(odd)

    def decode(self, ids) -> str:
        """The text of ids; its leading mark goes, and bytes that are no UTF-8 become U+FFFD."""
        out, raw = [], bytearray()
        low = self.byte_ids[0]
        for i in ids:
            if low <= i < low + 256:
                raw.append(i - low)
                continue
            if raw:
                out.append(raw.decode("utf-8", "replace"))
                raw.clear()
            out.append(self.texts[i])
        if raw:
            out.append(raw.decode("utf-8", "replace"))
        return "".join(out)[1:]


def load_pieces(path: str, score: str = "zipf") -> Pieces:
    """Pieces of a model file.  Control, unknown and unused pieces and runs of spaces take no part."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_proto=Path(path).read_bytes())
    size = model.get_piece_size()
    byte_ids = [model.piece_to_id(f"<0x{b:02X}>") for b in range(256)]
    if any(model.is_unknown(i) for i in byte_ids) or byte_ids != list(range(byte_ids[0], byte_ids[0] + 256)):
        raise ValueError("the vocabulary has no byte pieces in a row")
    texts, ids, scores = [""] * size, {}, {}
    plain = []
    for i in range(size):
        if model.is_control(i) or model.is_unknown(i) or model.is_unused(i) or model.is_byte(i):
            continue
        piece = model.id_to_piece(i)
        texts[i] = piece.replace(SPACE, " ")
        if SPACE not in piece[1:]:
            plain.append((piece, i, model.get_score(i)))
    norm = float(np.log(np.sum(1.0 / (np.arange(len(plain) + 1) + 10.0))))
    for rank, (piece, i, own) in enumerate(sorted(plain, key=lambda p: (-p[2], p[1]))):
        ids[piece] = i
        scores[piece] = float(own) if score == "model" else -float(np.log(rank + 10.0)) - norm
    worst = min(scores.values())
    found = np.zeros(len(ids), dtype=np.uint64)
    for k, piece in enumerate(ids):
        h = 0
        for c in piece:
            h = (h * int(_BASE) + ord(c) + 1) % 2**64
        found[k] = h
    found = mix64(found)
    order = np.argsort(found)
    buckets = np.searchsorted(found[order] >> np.uint64(64 - _BUCKET_BITS), np.arange((1 << _BUCKET_BITS) + 1, dtype=np.uint64)).astype(np.int32)
    table = found[order], np.array(list(scores.values()))[order], np.array(list(ids.values()), dtype=np.int64)[order], buckets
    return Pieces(ids, scores, texts, byte_ids, worst - 5.0, max(map(len, ids)), table)


def marked_words(text: str) -> list[str]:
    """Words of a text with their opening mark; they make up the whole marked text."""
    return [SPACE + w for w in text.replace(SPACE, _LITERAL).split(" ")] if text else []


def combined(losses: np.ndarray, words: list[str], searched: Callable[[str], list[tuple[float, tuple[int, ...]]]], n: int) -> list[tuple[float, tuple[tuple[int, int], ...]]]:
    """(loss, departures) of the n best ways of a text, from what each word's second best way loses.

    A departure is (word, rank): that word takes its way of that rank, 0 being the best.
    A way among the n best departs from the best one only in words whose second best
    loses least: n - 1 of them suffice.  Those are searched backward for their own n
    best.  Ties go to departures in earlier words.
    """
    if len(losses) >= n:
        least = np.partition(losses, n - 2)[n - 2]
        few = np.flatnonzero(losses < least)
        few = np.sort(np.concatenate([few, np.flatnonzero(losses == least)[: n - 1 - len(few)]]))
    else:
        few = np.arange(len(losses))
    ways: list[tuple[float, tuple[tuple[int, int], ...]]] = [(0.0, ())]
    for i in few[np.isfinite(losses[few])].tolist():
        if len(ways) == n and losses[i] >= ways[-1][0]:
            continue  # even its second best way alone is none of the n
        found = searched(words[i])
        top = found[0][0]
        own = [(0.0, ()), *[(round(top - found[rank][0], 9), ((i, rank),)) for rank in range(1, len(found))]]
        ways = sorted([(round(a + b, 9), x + y) for a, x in ways for b, y in own])[:n]
    return ways


class _Store:
    """Segmentations of the words met by one Python worker, as flat arrays by word number."""

    def __init__(self, pieces: Pieces):
        self.pieces = pieces
        self.clear()

    def clear(self) -> None:
        self.number: dict[str, int] = {}
        self.searched: dict[tuple[str, int], list[tuple[float, tuple[int, ...]]]] = {}
        self.best, self.loss, self.body, self.starts, self.sizes, self.exact = (np.zeros(0, t) for t in (float, float, np.int32, np.int64, np.int64, bool))

    def ways(self, n: int) -> Callable[[str], list[tuple[float, tuple[int, ...]]]]:
        """The n best ways of a word, searched once; of tied ways the one that stands here is the first."""

        def of(word: str) -> list[tuple[float, tuple[int, ...]]]:
            if (word, n) not in self.searched:
                found, k = self.pieces.nbest(word, n), self.number[word]
                own = tuple(self.body[self.starts[k] : self.starts[k] + self.sizes[k]].tolist())
                if found[0][1] != own:
                    found = [(found[0][0], own), *[f for f in found if f[1] != own]][:n]
                self.searched[word, n] = found
            return self.searched[word, n]

        return of

    def add(self, words: list[str]) -> None:
        found = self.pieces.many(words)
        self.number.update(zip(words, range(len(self.number), len(self.number) + len(words)), strict=True))
        low = self.pieces.byte_ids[0]
        texts = self.pieces.texts
        exact = np.empty(len(words), dtype=bool)
        body = found.body.tolist()
        spelled = np.concatenate([[0], np.cumsum((found.body >= low) & (found.body < low + 256))])
        plain = (spelled[found.starts + found.sizes] == spelled[found.starts]).tolist()
        for k, (w, a, m) in enumerate(zip(words, found.starts.tolist(), found.sizes.tolist(), strict=True)):
            own = body[a : a + m]
            # what the ids spell, against the word: pieces without bytes need no decoder
            exact[k] = ("".join([texts[i] for i in own]) if plain[k] else " " + self.pieces.decode(own)) == w.replace(SPACE, " ").replace(_LITERAL, SPACE)
        self.best = np.concatenate([self.best, found.best])
        self.loss = np.concatenate([self.loss, found.best - found.second])
        self.starts = np.concatenate([self.starts, found.starts + len(self.body)])
        self.body = np.concatenate([self.body, found.body])
        self.sizes = np.concatenate([self.sizes, found.sizes])
        self.exact = np.concatenate([self.exact, exact])

    def ids(self, at: np.ndarray) -> np.ndarray:
        sizes = self.sizes[at]
        ends = np.cumsum(sizes)
        return self.body[np.repeat(self.starts[at] - ends + sizes, sizes) + np.arange(int(ends[-1]) if len(ends) else 0)]

    def nbest(self, words: list[str], n: int, with_ids: bool) -> tuple[list[float], list[np.ndarray], list[str], bool]:
        """(scores, ids, digests of ids) of the n best ways of a text, best first, and whether its best ids spell it.

        Without ids, those of the best way alone come back; digests are made from its
        stretches and the words in which a way departs.
        """
        if not words:
            return [], [], [], True
        at = np.fromiter(map(self.number.__getitem__, words), np.int64, len(words))
        whole, of = self.ids(at), self.ways(n)
        best, body, width = float(self.best[at].sum()), memoryview(whole.tobytes()), whole.itemsize
        ends = np.cumsum(self.sizes[at])
        scores, ids, digests = [], [], []
        for loss, departures in combined(self.loss[at], words, of, n):
            parts, done = [], 0
            for i, rank in departures:
                end = int(ends[i])
                parts += [body[width * done : width * (end - int(self.sizes[at[i]]))], np.array(of(words[i])[rank][1], dtype=np.int32).tobytes()]
                done = end
            parts.append(body[width * done :])
            made = hashlib.sha1()
            for part in parts:
                made.update(part)
            scores.append(best - loss)
            digests.append(made.hexdigest())
            if with_ids or not ids:
                ids.append(np.frombuffer(b"".join(parts), dtype=np.int32) if departures else whole)
        return scores, ids, digests, bool(self.exact[at].all())


def encode_documents(df: DataFrame, pieces: Pieces, text_col: str = "text", *, n: int = 4, ids: str = "nbest", cache_words: int = 400_000) -> DataFrame:
    """Adds n_pieces, [ids, [nbest_ids,]] nbest_scores, nbest_digests, ids_digest and decoded.

    ``ids`` says which ids come back: "nbest" those of the n best ways (and of the best
    one alone), "best" only the latter, "none" the digests alone.  nbest columns are best
    first, with fewer than n entries where a text has fewer ways; ties go to ways that
    depart in earlier words, and in a word to the one that the search meets first.  Digests are of the ids as
    32-bit little-endian numbers (SHA-1).  ``decoded`` says whether the ids give back the
    whole text.  Null and empty texts have no pieces and no ways, and decode to
    themselves.  Texts of any length are encoded whole.  Columns of these names are
    replaced, others kept; repeated rows encode alike; an empty table stays empty.
    """
    one = T.ArrayType(T.IntegerType())
    shown = {"nbest": [("ids", one), ("nbest_ids", T.ArrayType(one))], "best": [("ids", one)], "none": []}[ids]
    fields = [("n_pieces", T.LongType()), *shown, ("nbest_scores", T.ArrayType(T.DoubleType())), ("nbest_digests", T.ArrayType(T.StringType())), ("ids_digest", T.StringType()), ("decoded", T.BooleanType())]
    types = [pa.int64(), *[pa.list_(pa.int32()), pa.list_(pa.list_(pa.int32()))][: len(shown)], pa.list_(pa.float64()), pa.list_(pa.string()), pa.string(), pa.bool_()]
    store: list[_Store] = []  # made in the worker
    nothing = np.zeros(0, np.int32)
    empty = hashlib.sha1(b"").hexdigest()

    def make(batch: pa.RecordBatch) -> list:
        if not store:
            store.append(_Store(pieces))
        known = store[0]
        column = batch.column(batch.schema.names.index(text_col))
        rows = []
        for low in range(0, len(column), 1024):
            texts = [x.as_py() or "" for x in column[low : low + 1024]]
            split = [marked_words(t) for t in texts]
            if len(known.number) > cache_words:
                known.clear()
            if new := list(set(itertools.chain.from_iterable(split)) - known.number.keys()):
                known.add(new)
            for words in split:
                scores, ways, digests, exact = known.nbest(words, n, len(shown) > 1)
                best = ways[0] if ways else nothing
                rows.append((len(best), *[best, ways][: len(shown)], scores, digests, digests[0] if ways else empty, exact))
        return [pa.array([r[i] for r in rows], t) for i, t in enumerate(types)]

    return add_columns(df, fields, make)


def decode_documents(df: DataFrame, pieces: Pieces, ids_col: str = "ids", text_col: str = "text") -> DataFrame:
    """Replaces or adds ``text_col``: the text that a column of ids spells.

    Null ids give null, no ids the empty text; ids that no piece has raise an error.  A
    literal mark of spaces, which is spelled by its bytes, comes back as itself.  Other
    columns are kept, repeated rows too; an empty table stays empty.
    """

    def make(batch: pa.RecordBatch) -> list:
        column = batch.column(batch.schema.names.index(ids_col))
        return [pa.array([None if x is None else pieces.decode(x) if x else "" for x in (v.as_py() for v in column)], pa.string())]

    return add_columns(df, [(text_col, T.StringType())], make)
