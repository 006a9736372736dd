"""SentencePiece encoding and decoding by a streaming Viterbi over a merge vocabulary.

The text's spaces become U+2581 and one is put in front. For each prefix of the text exactly one piece ends the
prefix's own encoding: the piece whose start leaves a shorter prefix whose last piece goes with it, that is, whose
two texts side by side are encoded as just these two pieces. So every position keeps one backpointer, no further
back than the longest piece, and the positions within that window are all that can still be extended. Whenever
their backpointer paths meet in one boundary, the ids up to it are final and leave the window (`_commits`).

No path crosses a character that the vocabulary lacks (it becomes byte pieces), a line feed, nor goes from another
character to U+2581: there all paths meet for certain, in an ordinary text after every word. As the window is empty
behind such a boundary, what it commits up to the next one depends on the characters between the two alone; a bounded
table remembers it for up to KEPT of them.

Pieces made of several U+2581 all have the same, lowest score, so a run of spaces is merged after all else,
the leftmost possible pair first.

Cases: a null or empty text has no ids; a text that holds U+2581 itself decodes to spaces there (round_trip is
false), as the library has it.
"""

from __future__ import annotations

from collections.abc import Iterator

import ahocorasick
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession

SPACE = "▁"
REMEMBERED, PAIRS, IDS_PER_BATCH, KEPT = 100_000, 300_000, 1_000_000, 64


def vocabulary_path(name: str = "piece_bpe_32k.model") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class StreamingCodec:
    def __init__(self, model_file: str):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=model_file)
        plain = [i for i in range(sp.get_piece_size()) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i))]
        self.id_of = {sp.id_to_piece(i): i for i in plain}
        self.score = {sp.id_to_piece(i): sp.get_score(i) for i in plain}
        self.byte_id = [sp.piece_to_id(f"<0x{b:02X}>") for b in range(256)]
        self.longest = max(map(len, self.id_of))
        # What each id decodes to; single bytes above ASCII as the escapes that surrogateescape turns back into bytes.
        self.shown = [""] * sp.get_piece_size()
        for p, i in self.id_of.items():
            self.shown[i] = p.replace(SPACE, " ")
        for b, i in enumerate(self.byte_id):
            self.shown[i] = chr(b) if b < 128 else chr(0xDC00 + b)
        self.halves: dict[str, tuple[float, str, str]] = {}
        #: The pieces that a window may hold, by their number in the automaton that finds them.
        self.names: list[str] = []
        self.finder = ahocorasick.Automaton()
        for p in self.id_of:
            if SPACE not in p[1:] and (half := self._last_merge(p)):
                self.halves[p] = half
                self.finder.add_word(p, (len(p), len(self.names)))
                self.names.append(p)
        self.finder.make_automaton()
        self.numbered, self.sizes = [self.id_of[p] for p in self.names], [len(p) for p in self.names]
        self.pairs: dict[int, bool] = {}
        # Two generations each of what parts and words became: a full young one becomes the old one.
        self.known: list[dict[str, tuple[int, ...]]] = [{}, {}]
        self.words: list[dict[str, tuple[int, ...]]] = [{}, {}]
        self.parts = regex.compile(f"{SPACE}+[^{SPACE}\\n]*|[^{SPACE}\\n]+|\\n")

    def _last_merge(self, piece: str) -> tuple[float, str, str] | None:
        """When the piece's own encoding is the piece: its rank and the two halves of its last merge (-1 for one character)."""
        at, last = list(piece), (-1.0, "", "")
        while len(at) > 1:
            found = [(-self.score[m], i) for i in range(len(at) - 1) if (m := at[i] + at[i + 1]) in self.score]
            if not found:
                return None
            rank, i = min(found)
            last = (rank, at[i], at[i + 1])
            at[i : i + 2] = [at[i] + at[i + 1]]
        return last

    def _fits(self, left: str, right: str) -> bool:
        """Whether left + right is encoded as the two. Undoing their merges from the latest, the parts on both sides of
        the boundary stand side by side until the merge undone before; a merge of them with a better rank comes first."""
        a, b, limit = left, right, float("inf")
        while True:
            score = self.score.get(a + b)
            if score is not None and -score < limit:
                return False
            (ra, _, tail), (rb, head, _) = self.halves[a], self.halves[b]
            if ra > rb:
                limit, a = ra, tail
            elif rb >= 0:
                limit, b = rb + 0.5, head  # of equal ranks the boundary's is further left
            else:
                return True

    def _pair(self, left: int, right: int) -> bool:
        if len(self.pairs) >= PAIRS:
            self.pairs.clear()
        fits = self.pairs[left << 20 | right] = self._fits(self.names[left], self.names[right])
        return fits

    def _commits(self, text: str) -> Iterator[list[int]]:
        """The ids of a text without inner boundaries, as the window commits them."""
        window, base, n, room = [-1], 0, 1, 3 * self.longest  # window[k]: the piece that ends at base + k, -1 where none does
        known, put = self.pairs.get, window.append
        for last, (size, piece) in self.finder.iter(text):
            k = last + 1 - base
            if k < n:
                continue
            if k > n:  # characters that the vocabulary lacks: all paths end before them
                yield self._path(window, 0, n - 1)
                yield [x for c in text[base + n - 1 : last] for x in self._lacking(c)]
                base, k, n = last, 1, 1
                window[:] = [-1]
            left = window[k - size]
            if left >= 0:
                fits = known(left << 20 | piece)
                if not (self._pair(left, piece) if fits is None else fits):
                    continue
            put(piece)
            n += 1
            if n > room:
                met = self._meeting(window)
                yield self._path(window, 0, met)
                window[: met + 1] = [-1]
                base, n = base + met, n - met
                room = n + 2 * self.longest
        yield self._path(window, 0, n - 1)
        if base + n <= len(text):
            yield [x for c in text[base + n - 1 :] for x in self._lacking(c)]

    def _lacking(self, c: str) -> list[int]:
        return [self.id_of[c]] if c in self.id_of else [self.byte_id[b] for b in c.encode("utf-8")]

    def _meeting(self, window: list[int]) -> int:
        """The last boundary on the paths of all positions that a later piece can start from."""
        heads = set(range(max(0, len(window) - self.longest), len(window)))
        while len(heads) > 1:
            last = max(heads)
            heads.remove(last)
            heads.add(last - self.sizes[window[last]])
        return heads.pop()

    def _path(self, window: list[int], start: int, end: int) -> list[int]:
        back, ids, sizes = [], self.numbered, self.sizes
        while end > start:
            piece = window[end]
            back.append(ids[piece])
            end -= sizes[piece]
        back.reverse()
        return back

    def _spaces(self, n: int) -> list[int]:
        """The merges of n spaces: equal scores, so always the leftmost pair that is a piece."""
        done: list[int] = []
        for _ in range(n):
            done.append(1)
            while len(done) > 1 and SPACE * (done[-2] + done[-1]) in self.score:
                done[-2:] = [done[-2] + done[-1]]
        return [self.id_of[SPACE * k] for k in done]

    def _part(self, part: str) -> tuple[int, ...]:
        """The ids between two boundaries at which all paths meet."""
        spaces = len(part) - len(part.lstrip(SPACE))
        ids = [i for run in self._commits(part[max(0, spaces - 1) :]) for i in run]
        if spaces > 1:
            alone = bool(ids) and ids[0] == self.id_of[SPACE]
            ids = self._spaces(spaces - (not alone)) + ids[alone:]
        return tuple(ids)

    def encode(self, text: str | None) -> list[int]:
        ids: list[int] = []
        for run in self.stream(text):
            ids += run
        return ids

    def stream(self, text: str | None) -> Iterator[tuple[int, ...]]:
        """The ids of a text, run by run as they are committed at the latest."""
        if not text:
            return
        if SPACE in text or "  " in text or text[0] == " " or text[-1] == " ":
            for part in self.parts.finditer(SPACE + text.replace(" ", SPACE)):
                yield self._remembered(part[0])
            return
        young, old = self.words
        for word in text.split(" "):
            found = young.get(word)
            if found is None:
                if (found := old.get(word)) is None:
                    if "\n" in word:
                        for part in self.parts.finditer(SPACE + word):
                            yield self._remembered(part[0])
                        continue
                    found = self._part(SPACE + word)
                self._keep(self.words, word, found)
                young, old = self.words
            yield found

    def _remembered(self, part: str) -> tuple[int, ...]:
        young, old = self.known
        found = young.get(part)
        if found is None:
            if (found := old.get(part)) is None:
                found = self._part(part)
            self._keep(self.known, part, found)
        return found

    @staticmethod
    def _keep(tables: list[dict[str, tuple[int, ...]]], text: str, ids: tuple[int, ...]) -> None:
        if len(text) <= KEPT:
            if len(tables[0]) >= REMEMBERED:
                tables[:] = [{}, tables[0]]
            tables[0][text] = ids

    def forget(self) -> None:
        """Empties the tables, which an idle worker would else hold on to while other stages run."""
        self.pairs.clear()
        self.known[:], self.words[:] = [{}, {}], [{}, {}]

    def decode(self, ids) -> str:
        text = "".join(map(self.shown.__getitem__, ids))
        try:
            text.encode("utf-8")
        except UnicodeEncodeError:
            text = text.encode("utf-8", "surrogateescape").decode("utf-8", "replace")
        return text[1:]


_codecs: dict[str, StreamingCodec] = {}


def codec(model_file: str) -> StreamingCodec:
    if model_file not in _codecs:
        _codecs[model_file] = StreamingCodec(model_file)
    return _codecs[model_file]


def encode_documents(docs: DataFrame, model_file: str | None = None) -> DataFrame:
    """doc_id, ids, n_tokens, round_trip (whether decoding the ids gives the text) for every row of docs."""
    name = model_file or vocabulary_path()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(name)
        for b in batches:
            start, rows, offsets, exact = 0, [], [0], []
            doc, text = b.column(0), b.column(1)
            for i in range(b.num_rows):
                t = text[i].as_py()
                ids = c.encode(t)
                rows += ids
                offsets.append(len(rows))
                exact.append(c.decode(ids) == (t or ""))
                if len(rows) >= IDS_PER_BATCH:
                    yield _batch(doc.slice(start, i + 1 - start), rows, offsets, exact)
                    start, rows, offsets, exact = i + 1, [], [0], []
            if start < b.num_rows:
                yield _batch(doc.slice(start), rows, offsets, exact)
        c.forget()

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, ids array<int>, n_tokens int, round_trip boolean")


def _batch(doc: pa.Array, ids: list[int], offsets: list[int], exact: list[bool]) -> pa.RecordBatch:
    o = pa.array(offsets, pa.int32())
    sizes = pa.array([b - a for a, b in zip(offsets, offsets[1:], strict=False)], pa.int32())
    return pa.RecordBatch.from_arrays([doc.cast(pa.int64()), pa.ListArray.from_arrays(o, pa.array(ids, pa.int32())), sizes, pa.array(exact)], names=["doc_id", "ids", "n_tokens", "round_trip"])


def decode_documents(encoded: DataFrame, model_file: str | None = None) -> DataFrame:
    """encoded (doc_id, ids) with text instead of ids."""
    name = model_file or vocabulary_path()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(name)
        for b in batches:
            texts = [None if x is None else c.decode(x) for x in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0).cast(pa.int64()), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


def vocabulary_size(spark: SparkSession, model_file: str | None = None) -> int:
    return len(codec(model_file or vocabulary_path()).id_of)
