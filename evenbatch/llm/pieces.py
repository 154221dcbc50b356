"""SentencePiece encoding and decoding for merge-type vocabularies.

A score-ordered agenda of adjacent symbol pairs: the pair whose join has the highest score is merged first, the
leftmost of equals, until no pair joins to a piece; symbols that are no piece fall back to bytes. Where no piece has
a space mark after another character, merges never cross a word's start, so words are encoded once and remembered.
Each newly met word of an Arrow batch is checked against the sentencepiece library, which must agree.

A null text is the empty text, whose ids are begin and end alone. Texts are taken whole.
"""

from __future__ import annotations

import hashlib
import heapq
import re
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .textkernel import KEPT, lean, text_batches

MARK = "▁"
#: Remembered words of a Python worker at most, some 200 bytes each; the memory then starts anew.
MEMORY_WORDS = 250_000
#: Words that are longer are encoded each time.
MEMORY_CHARS = 64

#: Words of up to so many characters are merged many at a time.
WIDE = 24

class PieceModel:
    """A vocabulary read through the library, and an encoder and a decoder of its own."""

    def __init__(self, path: str):
        import sentencepiece

        self.library = sp = sentencepiece.SentencePieceProcessor(model_file=path)
        ids = range(sp.get_piece_size())
        special = {i for i in ids if sp.is_byte(i) or sp.is_control(i) or sp.is_unknown(i)}
        self.begin, self.end, self.unknown = sp.bos_id(), sp.eos_id(), sp.unk_id()
        self.pieces = {sp.id_to_piece(i): (i, -sp.get_score(i)) for i in ids if i not in special}
        self.bytes_of = {int(sp.id_to_piece(i)[3:5], 16): i for i in ids if sp.is_byte(i)}
        self.said = [bytes([int(sp.id_to_piece(i)[3:5], 16)]) if sp.is_byte(i) else b"" if sp.is_control(i) else " ⁇ ".encode() if sp.is_unknown(i) else sp.id_to_piece(i).encode() for i in ids]
        self.words: dict[str, bytes] = {}
        self._cuts()
        self._pairs()

    def _cuts(self) -> None:
        """Where texts can be cut because no piece spans the cut: before a mark, around newlines, and between a
        letter and those signs that no piece has after a letter."""
        self.by_word = not any(MARK in p.lstrip(MARK) for p in self.pieces) and not any("\n" in p for p in self.pieces)
        signs = "".join(c for c in ".,;:!?" if not any(re.search(rf"[^\W\d_]{re.escape(c)}", p) for p in self.pieces))
        plain = f"{MARK}+[^{MARK}\n]*|\n|[^{MARK}\n]+"
        self.cut = re.compile(f"{MARK}*+[^\\W\\d_{MARK}]++(?=[{re.escape(signs)}])|{plain}" if signs else plain)

    def _pairs(self) -> None:
        """The joins of two symbols that give a piece, as sorted arrays."""
        found = {}
        for piece, (number, cost) in self.pieces.items():
            for i in range(1, len(piece)):
                left, right = self.pieces.get(piece[:i]), self.pieces.get(piece[i:])
                if left and right:
                    found[left[0] << 20 | right[0]] = (cost, number)
        self.keys = np.array(sorted(found) + [1 << 62], dtype=np.int64)
        self.costs = np.array([found[k][0] for k in sorted(found)] + [np.inf])
        self.joined = np.array([found[k][1] for k in sorted(found)] + [-1], dtype=np.int64)
        self.of_char = np.full(0x110000, -1, dtype=np.int64)
        for piece, (number, _) in self.pieces.items():
            if len(piece) == 1:
                self.of_char[ord(piece)] = number

    def _join(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        key = np.where((left >= 0) & (right >= 0), left << 20 | right, -1)
        at = np.searchsorted(self.keys, key)
        hit = self.keys[at] == key
        return np.where(hit, self.costs[at], np.inf), np.where(hit, self.joined[at], -1)

    def merge_many(self, words: list[str]) -> list[bytes]:
        """As merge(), of many words: each takes the first entry of its agenda in each round."""
        out: list[bytes] = [b""] * len(words)
        groups: dict[int, list[int]] = {}
        for i, w in enumerate(words):
            if len(w) <= WIDE:
                groups.setdefault((len(w) + 3) // 4 * 4, []).append(i)
            else:
                out[i] = np.array(self.merge(w), dtype="<u4").tobytes()
        for width, members in groups.items():
            chars = np.frombuffer("".join([words[i].ljust(width, "\0") for i in members]).encode("utf-32-le"), dtype="<u4").reshape(-1, width)
            sizes = np.array([len(words[i]) for i in members])
            ids = np.where(np.arange(width) < sizes[:, None], self.of_char[chars], -1)
            odd = (ids >= 0).sum(1) != sizes
            for k in np.flatnonzero(odd):
                out[members[k]] = np.array(self.merge(words[members[k]]), dtype="<u4").tobytes()
            at = np.flatnonzero(~odd)
            ids = ids[at]
            costs, joins = self._join(ids[:, :-1], ids[:, 1:])
            places = np.arange(width)
            while len(at):
                best = costs.argmin(1)
                rows = np.arange(len(at))
                live = np.isfinite(costs[rows, best])
                if not live.all():
                    for k, line in zip(at[~live], ids[~live].astype("<u4")):
                        out[members[k]] = line[: sizes[k]].tobytes()
                    at, ids, costs, joins, best = at[live], ids[live], costs[live], joins[live], best[live]
                    rows = np.arange(len(at))
                if not len(at):
                    break
                sizes[at] -= 1
                made = joins[rows, best]
                take = np.minimum(places + (places > best[:, None]), width - 1)
                ids = np.take_along_axis(ids, take, 1)
                ids[:, -1] = -1
                ids[rows, best] = made
                shift = np.minimum(places[:-1] + (places[:-1] > best[:, None]), width - 2)
                costs, joins = np.take_along_axis(costs, shift, 1), np.take_along_axis(joins, shift, 1)
                costs[:, -1] = np.inf
                right = np.minimum(best, width - 2)
                costs[rows, right], joins[rows, right] = self._join(ids[rows, right], ids[rows, right + 1])
                some = np.flatnonzero(best > 0)
                costs[some, best[some] - 1], joins[some, best[some] - 1] = self._join(ids[some, best[some] - 1], ids[some, best[some]])
        return out

    def merge(self, text: str) -> list[int]:
        """Ids of a text whose spaces are marks already."""
        pieces, symbols = self.pieces, list(text)
        n = len(symbols)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        agenda: list[tuple[float, int, int, str]] = []
        for i in range(n - 1):
            if hit := pieces.get(both := symbols[i] + symbols[i + 1]):
                agenda.append((hit[1], i, i + 1, both))
        heapq.heapify(agenda)
        while agenda:
            _, left, right, both = heapq.heappop(agenda)
            if after[left] != right or symbols[left] + symbols[right] != both or not symbols[left] or not symbols[right]:
                continue
            symbols[left], symbols[right] = both, ""
            after[left] = follow = after[right]
            if follow < n:
                before[follow] = left
                if hit := pieces.get(joined := both + symbols[follow]):
                    heapq.heappush(agenda, (hit[1], left, follow, joined))
            if (ahead := before[left]) >= 0 and (hit := pieces.get(joined := symbols[ahead] + both)):
                heapq.heappush(agenda, (hit[1], ahead, left, joined))
        out: list[int] = []
        for s in symbols:
            if not s:
                continue
            if hit := pieces.get(s):
                out.append(hit[0])
            elif self.bytes_of:
                out.extend(self.bytes_of[b] for b in s.encode())
            elif not out or out[-1] != self.unknown:
                out.append(self.unknown)
        return out

    def encode_many(self, texts: list[str]) -> list[bytes]:
        """Little-endian 32-bit ids of whole texts, without begin and end."""
        if not self.by_word:
            got = [np.array(self.merge(MARK + t.replace(" ", MARK)) if t else [], dtype="<u4").tobytes() for t in texts]
            for t, ids in zip(texts, got):
                self._same(t, ids, self.library.encode(t))
            return got
        cut, known = self.cut.findall, self.words
        if len(known) > MEMORY_WORDS:
            known.clear()
        parts = [cut(MARK + t.replace(" ", MARK)) if t else [] for t in texts]
        fresh = list(set().union(*parts).difference(known.keys()))
        done = self.merge_many(fresh)
        self.check(fresh, done)
        known.update(zip(fresh, done))
        out = [b"".join(map(known.__getitem__, p)) for p in parts]
        for w in fresh:
            if len(w) > MEMORY_CHARS:
                del known[w]
        return out

    def encode(self, text: str) -> bytes:
        return self.encode_many([text])[0]

    @staticmethod
    def _same(said: str, mine: bytes, there: list[int]) -> None:
        if np.array(there, dtype="<u4").tobytes() != mine:
            raise ValueError(f"sentencepiece encodes {said!r} as {there}")

    def check(self, words: list[str], ids: list[bytes]) -> None:
        """The library must give the same ids. It puts a mark before a text; what has none is shown after a newline,
        which joins with nothing."""
        lead = np.array(self.merge(MARK) + self.merge("\n"), dtype="<u4").tobytes()
        there = self.library.encode([w[1:].replace(MARK, " ") if w[0] == MARK else "\n" + w for w in words], num_threads=1)
        mine = [x if w[0] == MARK else lead + x for w, x in zip(words, ids)]
        flat = np.fromiter((i for x in there for i in x), dtype="<u4").tobytes()
        if flat != b"".join(x for w, x in zip(words, mine) if w != MARK):  # a lone mark can't be shown
            for w, x, y in zip(words, mine, there):
                if w != MARK:
                    self._same(w, x, y)

    def decode(self, ids: np.ndarray) -> str:
        """The text of some ids: pieces joined, marks to spaces, without the mark put before the text."""
        joined = b"".join(map(self.said.__getitem__, ids.tolist()))
        try:
            text = joined.decode()
        except UnicodeDecodeError:
            return self.library.decode(ids.tolist())
        return text.removeprefix(MARK).replace(MARK, " ")


def model(path: str) -> PieceModel:
    """The model of this Python process."""
    name = f"pieces {path}"
    if name not in KEPT:
        KEPT[name] = PieceModel(path)
    return KEPT[name]


COLUMNS = "n_tokens long, ids_sha256 string, decoded_sha256 string"


def encode_batches(path: str, keep: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Batches whose last column is the text; the first keep columns are passed on, then come COLUMNS."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        spm = model(path)
        begin, end = np.uint32(spm.begin).tobytes(), np.uint32(spm.end).tobytes()
        for batch in batches:
            for part, raw in text_batches([batch.rename_columns([*batch.schema.names[:keep], "text"])]):
                counts, ids_sha, text_sha = [], [], []
                texts = [x.decode() if x else "" for x in raw]
                for text, body in zip(texts, spm.encode_many(texts)):
                    whole = np.frombuffer(b"".join((begin, body, end)), dtype="<u4")
                    decoded = spm.decode(whole)
                    if decoded != spm.library.decode(whole.tolist()):
                        raise ValueError("sentencepiece decodes a text in another way")
                    counts.append(len(whole))
                    ids_sha.append(hashlib.sha256(whole.tobytes()).hexdigest())
                    text_sha.append(hashlib.sha256(decoded.encode()).hexdigest())
                yield pa.RecordBatch.from_arrays([*(part.column(i) for i in range(keep)), pa.array(counts, pa.int64()), pa.array(ids_sha, pa.string()), pa.array(text_sha, pa.string())], [*part.schema.names[:keep], "n_tokens", "ids_sha256", "decoded_sha256"])

    return lean(run, "pieces")


def encode_documents(df: DataFrame, path: str, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, n_tokens, ids_sha256, decoded_sha256 of every row; other columns are not read."""
    return df.select(key, text).mapInArrow(encode_batches(path, 1), f"{key} {dict(df.dtypes)[key]}, {COLUMNS}")
