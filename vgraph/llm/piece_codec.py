"""Encoding and decoding with a piece vocabulary: streaming Viterbi over a bounded window.

The lattice of a text has a node per character boundary and an edge per vocabulary piece. Two kinds
of model decide which path survives:

* ``score`` (unigram models): the path of the greatest score sum.
* ``merge`` (byte-pair models): the path in which every two neighbouring pieces are such that
  merging their joint text gives just these two. Exactly one piece survives at each boundary,
  and the surviving path spells the ids that rank-ordered merging gives.

A piece is at most ``longest`` characters, so only that many boundaries can be continued. Once
the back-pointers of all of them meet in one boundary, the ids before it are final: they are
emitted and the window forgets them, so memory does not grow with the text.

A character pair that occurs inside no piece forces such a convergence. The whole text goes through the stream; what the lattice gave
for a short stretch between two forced boundaries is remembered in a bounded memo, so that it is walked once while it is remembered.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from functools import lru_cache
from operator import itemgetter
from struct import pack as struct_pack

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import BIN, LONG, Memo, map_rows, struct, texts

SPACE = "▁"
MEMO = 150_000


def model_path(name: str = "piece_bpe_32k.model") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def _varint(b: bytes, i: int) -> tuple[int, int]:
    out = shift = 0
    while True:
        out |= (b[i] & 127) << shift
        shift += 7
        i += 1
        if b[i - 1] < 128:
            return out, i


def _fields(b: bytes) -> Iterator[tuple[int, object]]:
    i = 0
    while i < len(b):
        key, i = _varint(b, i)
        if key & 7 == 0:
            v, i = _varint(b, i)
        elif key & 7 == 2:
            n, i = _varint(b, i)
            v, i = b[i : i + n], i + n
        else:
            n = 8 if key & 7 == 1 else 4
            v, i = b[i : i + n], i + n
        yield key >> 3, v


class Codec:
    """``encode`` and ``decode`` for one model file; ``kind`` overrides what the file says ('score' or 'merge')."""

    def __init__(self, path: str, kind: str | None = None, memo: int = MEMO):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        spec = dict(_fields(sp.serialized_model_proto()))
        train, norm = dict(_fields(spec.get(2, b""))), dict(_fields(spec.get(3, b"")))
        self.kind = kind or {1: "score", 2: "merge"}[train.get(3, 1)]
        if norm.get(2) or norm.get(4, 1):
            raise ValueError("only models whose normaliser keeps the text as it is are handled")
        self.prefix = bool(norm.get(3, 1))
        n = sp.get_piece_size()
        self.pieces = [sp.id_to_piece(i) for i in range(n)]
        self.bytes_ = {}
        self.ids: dict[str, int] = {}
        self.score: dict[str, float] = {}
        self.raw: list[bytes] = []
        for i, p in enumerate(self.pieces):
            if sp.is_byte(i):
                self.bytes_[int(p[3:5], 16)] = i
                self.raw.append(bytes([int(p[3:5], 16)]))
            elif sp.is_control(i):
                self.raw.append(b"")
            elif sp.is_unknown(i):
                self.unk = i
                self.raw.append(" ⁇ ".encode())
            else:
                self.ids[p] = i
                self.score[p] = sp.get_score(i)
                self.raw.append(p.encode())
        self.longest = max(map(len, self.ids), default=1)
        self.unknown = min(self.score.values(), default=0.0) - 10.0
        self.cut = self._cutter()
        self.memo = Memo(self._coded, memo, 64)
        self.split = _Splits(self)
        self.automaton = self._automaton()
        self.most = memo
        self.fits: dict[tuple[str, str], bool] = {}
        self.sizes = np.array(list(map(len, self.raw)), np.int64)
        self.starts = np.cumsum(self.sizes) - self.sizes
        self.pool = np.frombuffer(b"".join(self.raw), np.uint8)
        #: Characters that went through the lattice, its commits, and the most boundaries it held at once.
        self.streamed = self.commits = self.widest = 0

    def _cutter(self) -> re.Pattern:
        """Splits a text at boundaries that no piece crosses, as far as the vocabulary allows."""
        pairs = {(a, b) for p in self.ids for a, b in zip(p, p[1:], strict=False)}
        if any(b == SPACE != a for a, b in pairs):
            return re.compile(".+", re.S)
        alone = "" if any("\n" in x for x in pairs) else "\n"
        if any(a.isalpha() != b.isalpha() and a != SPACE for a, b in pairs):
            return re.compile(f"{SPACE}*[^{SPACE}{alone}]+|{SPACE}+|[{alone or SPACE}]", re.S)
        other = "".join(sorted({c for p in self.ids for c in p if c.isalnum() and not c.isalpha() and not c.isdecimal()}))
        return re.compile(rf"{SPACE}*[^\W\d_{other}]+|{SPACE}*(?:[^{SPACE}{alone}\w]|[\d_{other}])+|{SPACE}+|[{alone or SPACE}]", re.S)

    def _automaton(self):
        """Finds the pieces that a path may use at each boundary; by merging, only those that merging makes."""
        import ahocorasick

        out = ahocorasick.Automaton()
        for p in self.ids:
            if self.kind != "merge" or len(p) == 1 or self.split[p]:
                out.add_word(p, p)
        out.make_automaton()
        return out

    # -- merging, for the pair test ------------------------------------------------------------
    def merged(self, text: str) -> tuple[list[str], tuple[str, str]]:
        """Rank-ordered merging of a short text (best score first, leftmost among equals), and the two parts merged last."""
        parts, last, score = list(text), ("", ""), self.score
        while len(parts) > 1:
            best, at = None, -1
            for i in range(len(parts) - 1):
                s = score.get(parts[i] + parts[i + 1])
                if s is not None and (best is None or s > best):
                    best, at = s, i
            if at < 0:
                break
            last = parts[at], parts[at + 1]
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts, last

    def pair(self, a: str, b: str) -> bool:
        """Whether merging the joint text of two pieces gives these two.

        Undoing the later merge first, the piece parts that ever met at the joint are tried: the joint is crossed if
        their joint piece would have come before the merges that took either part away from it."""
        ok = self.fits.get((a, b))
        if ok is not None:
            return ok
        if len(self.fits) >= self.most:
            self.fits.clear()
        if SPACE + SPACE in a or SPACE + SPACE in b:  # runs of spaces share one score
            ok = self.merged(a + b)[0] == [a, b]
        else:
            score, split, x, y, gone_x, gone_y, ok = self.score, self.split, a, b, -1e300, -1e300, True
            while True:
                s = score.get(x + y)
                if s is not None and s > gone_x and s >= gone_y:
                    ok = False
                    break
                sx, sy = len(x) > 1 and score[x], len(y) > 1 and score[y]
                if sx is False and sy is False:
                    break
                if sy is False or (sx is not False and sx < sy):
                    gone_x, x = sx, split[x][1]
                else:
                    gone_y, y = sy, split[y][0]
        self.fits[a, b] = ok
        return ok

    # -- the streaming lattice -----------------------------------------------------------------
    def _shared(self, last: list[str], final: bool) -> list[str]:
        """The pieces that all surviving paths share from the window's start on, taken out of the window.

        ``last`` holds the last piece for each boundary of the window; those that a piece can still continue survive, or only the
        last one where the stretch has ended."""
        n = len(last)
        meet = n
        if not final:
            live = set(range(max(0, n - self.longest + 1), n + 1))
            while len(live) > 1:
                meet = max(live)
                live.discard(meet)
                live.add(meet - len(last[meet - 1]))
            meet = live.pop()
        path = []
        at = meet
        while at:
            path.append(last[at - 1])
            at -= len(path[-1])
        if path:
            self.commits += 1
            self.widest = max(self.widest, n)
            del last[:meet]
        path.reverse()
        return path

    def lattice(self, text: str, every: int = 32) -> Iterator[str]:
        """Pieces of a stretch, each yielded as soon as all surviving paths agree on it (looked for every ``every`` boundaries).

        The automaton names the pieces that end at each boundary, the longest first; a character that is no piece stands for itself."""
        n, last, done, before, look = len(text), [], 0, "", every
        choose = (self._by_merging if self.kind == "merge" else self._by_score)(text, last, lambda: (done, before))
        for i in choose:
            if i >= look and i < n:
                look = i + every
                for p in self._shared(last, False):
                    yield p
                    done, before = done + len(p), p
        yield from self._shared(last, True)

    def _by_merging(self, text: str, last: list[str], state) -> Iterator[int]:
        """Enters into ``last``, boundary by boundary, the longest piece that merging would leave beside the piece before it."""
        fits, pair, at, n, i = self.fits, self.pair, 0, 0, 0
        done, before = 0, ""
        for e, p in self.automaton.iter(text):
            if e < i:
                continue
            while i < e:  # characters that are no piece
                last.append(text[i])
                i += 1
                yield i
                done, before = state()
            n = len(p)
            if n > 1:
                at = i + 1 - n
                if at < done:
                    continue
                if at:
                    a = last[at - done - 1] if at > done else before
                    ok = fits.get((a, p))
                    if not (pair(a, p) if ok is None else ok):
                        continue
            last.append(p)
            i += 1
            if not i & 31:
                yield i
                done, before = state()
        while i < len(text):
            last.append(text[i])
            i += 1

    def _by_score(self, text: str, last: list[str], state) -> Iterator[int]:
        """Enters into ``last``, boundary by boundary, the last piece of the path of the greatest score sum."""
        best, done, pieces = [0.0], 0, self.automaton.iter(text)
        e, p = next(pieces, (len(text), ""))
        for i in range(len(text)):
            top, choice = best[i - done] + self.score.get(text[i], self.unknown), text[i]
            while e == i:
                at = i + 1 - len(p)
                if at >= done and (v := best[at - done] + self.score[p]) > top:
                    top, choice = v, p
                e, p = next(pieces, (len(text), ""))
            best.append(top)
            last.append(choice)
            yield i + 1
            new, _ = state()
            del best[: new - done]
            done = new

    def _coded(self, stretch: str) -> bytes:
        """Ids of a stretch by the lattice."""
        self.streamed += len(stretch)
        out: list[int] = []
        for p in self.lattice(stretch):
            i = self.ids.get(p)
            if i is not None:
                out.append(i)
            elif self.bytes_:
                out.extend(map(self.bytes_.__getitem__, p.encode("utf-8", "surrogatepass")))
            else:
                out.append(self.unk)
        return struct_pack(f"<{len(out)}I", *out)

    def stream(self, text: str) -> Iterator[bytes]:
        """Ids of a whole text (little-endian unsigned 32-bit), stretch by stretch as they become final.

        Between two stretches all paths converge on one boundary whatever stands on either side, so the lattice starts anew there,
        and a stretch that was met before has the ids that the lattice gave it then."""
        if text:
            t = (SPACE if self.prefix else "") + text.replace(" ", SPACE)
            yield from map(self.memo.__getitem__, map(itemgetter(0), self.cut.finditer(t)))

    def encode(self, text: str) -> bytes:
        return b"".join(self.stream(text))

    def decode(self, ids) -> str:
        at = np.asarray(ids, np.int64)
        n = self.sizes[at]
        ends = np.cumsum(n)
        raw = self.pool[np.repeat(self.starts[at] - ends + n, n) + np.arange(int(ends[-1]) if len(ends) else 0)]
        text = raw.tobytes().decode("utf-8", "replace").replace(SPACE, " ")
        return text[1:] if self.prefix and text[:1] == " " else text


class _Splits(dict):
    """The two parts that a piece is merged from last; empty for a piece that merging never makes."""

    def __init__(self, codec: Codec):
        super().__init__()
        self.codec = codec

    def __missing__(self, piece: str):
        parts, last = self.codec.merged(piece)
        out = self[piece] = last if len(parts) == 1 else ()
        return out


@lru_cache(4)
def codec_for(path: str, kind: str | None = None) -> Codec:
    """One codec a process: Python workers serve many tasks."""
    return Codec(path, kind)


def encode(docs: DataFrame, path: str | None = None, kind: str | None = None) -> DataFrame:
    """(doc_id, ids array<int>) of every row's whole text; no ids for a null or empty text."""
    path = path or model_path()

    def begin():
        codec = codec_for(path, kind)
        return lambda cols: {"doc_id": cols["doc_id"], "ids": [np.frombuffer(codec.encode(t), "<i4") for t in cols["text"]]}

    return map_rows(texts(docs), begin, struct(doc_id=LONG, ids=T.ArrayType(T.IntegerType())), size=64)


def decode(coded: DataFrame, path: str | None = None) -> DataFrame:
    """(doc_id, text) from (doc_id, ids); null ids give an empty text."""
    path = path or model_path()

    def begin():
        codec = codec_for(path)
        return lambda cols: {"doc_id": cols["doc_id"], "text": [codec.decode(x or ()) for x in cols["ids"]]}

    return map_rows(coded.select(F.col("doc_id").cast("long").alias("doc_id"), "ids"), begin, struct(doc_id=LONG, text=T.StringType()), size=64)


def encode_digest(docs: DataFrame, path: str | None = None, with_ids: bool = False) -> DataFrame:
    """(doc_id, n_tokens, ids_crc32, round_trip[, ids]) in one pass: ids are encoded, decoded again and compared.

    ids_crc32 is over the ids as little-endian unsigned 32-bit integers; ``ids`` holds them in that form. round_trip is
    false only for texts that hold the vocabulary's own space mark."""
    path = path or model_path()

    def begin():
        codec = codec_for(path)

        def each(cols):
            raw = [codec.encode(t) for t in cols["text"]]
            back = [codec.decode(np.frombuffer(x, "<u4")) == t for x, t in zip(raw, cols["text"], strict=True)]
            out = {"doc_id": cols["doc_id"], "n_tokens": [len(x) // 4 for x in raw], "ids_crc32": list(map(zlib.crc32, raw)), "round_trip": back}
            return out | ({"ids": raw} if with_ids else {})

        return each

    kinds = {"doc_id": LONG, "n_tokens": LONG, "ids_crc32": LONG, "round_trip": T.BooleanType()} | ({"ids": BIN} if with_ids else {})
    return map_rows(texts(docs), begin, struct(**kinds), size=64)
