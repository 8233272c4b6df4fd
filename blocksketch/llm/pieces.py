"""SentencePiece encoding and decoding: an Aho-Corasick automaton over the pieces drives one Viterbi pass.

At each position the automaton's outputs (all pieces that end there, longest first) relax the best score of the
position; a character that no one-character piece covers has an edge of unknown score, written as its UTF-8 bytes'
pieces. The best segmentation is the one of the largest sum of piece scores; of equal sums the last piece is the
longest. The scores are those of the vocabulary file, whatever its kind; with a file made for merge ranks the ids are
the best by score, which need not be those of the merges.

No piece has U+2581 behind another character, so segments between such places are independent of each other, and their
results are remembered up to a bound. A vocabulary for which that doesn't hold is taken text by text.

Text form: U+0020 becomes U+2581, and one more goes in front of a text that is not empty. Decoding undoes both.
decode(encode(t)) is t for every text without U+2581 itself, which decodes to a space.

Defined results: null gives null ids and null text, empty gives no ids. Repeated rows are encoded each. Empty tables
give empty tables. Other columns are carried as they are.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import columns, small_batches, trim_memory

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
SPACE = "▁"
FLUSH = 2_000_000  # tokens in a batch that is handed back
REMEMBER = 300_000


def load_vocabulary(path: str = MODEL) -> dict:
    """{pieces, scores, kinds}; kinds: n normal, b byte, x other. Bounded by the file, so it can be sent to every executor."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    n = range(sp.get_piece_size())
    kinds = "".join("b" if sp.is_byte(i) else "x" if sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i) else "n" for i in n)
    return {"pieces": [sp.id_to_piece(i) for i in n], "scores": [sp.get_score(i) for i in n], "kinds": kinds}


class Codec:
    def __init__(self, vocabulary: dict, remember: int = REMEMBER):
        import ahocorasick

        self.pieces, kinds, scores = vocabulary["pieces"], vocabulary["kinds"], vocabulary["scores"]
        self.byte = {int(p[3:5], 16): i for i, (p, k) in enumerate(zip(self.pieces, kinds)) if k == "b"}
        self.byte_value = {i: v for v, i in self.byte.items()}
        self.unknown = min((s for s, k in zip(scores, kinds) if k == "n"), default=0.0) - 10.0
        self.automaton = ahocorasick.Automaton()
        chars = set()
        for i, (p, k) in enumerate(zip(self.pieces, kinds)):
            if k == "n":
                self.automaton.add_word(p, (len(p), scores[i], i))
                chars |= set(p)
        self.automaton.make_automaton()
        whole = any(SPACE in p.lstrip(SPACE) for p, k in zip(self.pieces, kinds) if k == "n")
        self.split = None if whole else re.compile(f"\n|{SPACE}*[^{SPACE}\n]+|{SPACE}+" if "\n" not in chars else f"{SPACE}*[^{SPACE}]+|{SPACE}+")
        self.known: dict[str, list[int]] = {}
        self.remember = remember

    def viterbi(self, text: str) -> list[int]:
        n = len(text)
        best, back, piece = [0.0] * (n + 1), [0] * (n + 1), [-1] * (n + 1)
        reached = 0  # positions up to here are settled
        low = float("-inf")
        unknown = self.unknown

        def settle(end: int, at: int, score: float, single: bool) -> None:
            if not single and best[end - 1] + unknown > score:
                best[end], back[end], piece[end] = best[end - 1] + unknown, end - 1, -1

        top, single = low, False
        for last, (size, score, i) in self.automaton.iter(text):
            end = last + 1
            while reached < end - 1:  # no piece, or no more, ends at the position before
                settle(reached + 1, 0, top, single)
                reached += 1
                top, single = low, False
            s = best[end - size] + score
            if s > top:
                top = best[end] = s
                back[end], piece[end] = end - size, i
            if size == 1:
                single = True
        while reached < n:
            settle(reached + 1, 0, top, single)
            reached += 1
            top, single = low, False
        out: list[int] = []
        while n:
            if piece[n] >= 0:
                out.append(piece[n])
            else:
                out.extend(self.byte.get(x, 0) for x in reversed(text[back[n] : n].encode()))
            n = back[n]
        return out[::-1]

    def encode(self, text: str) -> list[int]:
        if not text:
            return []
        t = SPACE + text.replace(" ", SPACE)
        if self.split is None:
            return self.viterbi(t)
        known, out = self.known, []
        for x in self.split.findall(t):
            ids = known.get(x)
            if ids is None:
                if len(known) >= self.remember:
                    known.clear()
                ids = self.viterbi(x)
                if len(x) <= 64:
                    known[x] = ids
            out += ids
        return out

    def decode(self, ids: list[int]) -> str:
        if self.byte_value.keys().isdisjoint(ids):
            text = "".join(map(self.pieces.__getitem__, ids))
        else:
            out, run = [], bytearray()
            for i in ids:
                if (b := self.byte_value.get(i)) is not None:
                    run.append(b)
                    continue
                if run:
                    out.append(run.decode("utf-8", "replace"))
                    run.clear()
                out.append(self.pieces[i])
            text = "".join([*out, run.decode("utf-8", "replace")])
        return text.replace(SPACE, " ").removeprefix(" ")


_CODEC: list = [None, None]


def _codec(shared) -> Codec:
    """One codec for a worker, kept from task to task."""
    if _CODEC[0] != shared.value["pieces"]:
        _CODEC[:] = shared.value["pieces"], Codec(shared.value)
    return _CODEC[1]


def _free(rows: DataFrame, names: list[str]) -> None:
    taken = {c.lower() for c in rows.columns} & set(names)
    if taken:
        raise ValueError(f"the table has columns {sorted(taken)} of its own; give other names for the new ones")


def encode_texts(docs: DataFrame, path: str = MODEL, text_col: str = "text", check: bool = False, ids_col: str = "ids", size_col: str = "n_tokens", check_col: str = "round_trip") -> DataFrame:
    """docs with ids array<int> and n_tokens int, and with check, round_trip boolean, behind its own columns. A table that has a column of such a name is an error before anything runs; the names are parameters."""
    small_batches(docs.sparkSession)
    own, added = docs.columns, [ids_col, size_col, *([check_col] if check else [])]
    _free(docs, added)
    shared = docs.sparkSession.sparkContext.broadcast(load_vocabulary(path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = _codec(shared)
        for b in batches:
            texts, n = b[text_col], b.num_rows
            start, rows, sizes, trips, tokens = 0, [], [], [], 0
            for i in range(n):
                t = texts[i].as_py()
                ids = None if t is None else codec.encode(t)
                rows.append(np.array(ids or [], dtype=np.int32))
                sizes.append(None if ids is None else len(ids))
                if check:
                    trips.append(None if t is None else codec.decode(ids) == t)
                tokens += len(rows[-1])
                if tokens >= FLUSH or i + 1 == n:
                    ends = pa.array(np.cumsum([0, *map(len, rows)]), pa.int32())
                    lists = pa.ListArray.from_arrays(ends, pa.array(np.concatenate(rows)), mask=pa.array([x is None for x in sizes]))
                    more = [lists, pa.array(sizes, pa.int32()), *([pa.array(trips, pa.bool_())] if check else [])]
                    yield pa.RecordBatch.from_arrays([*b.slice(start, i + 1 - start).columns, *more], [*own, *added])
                    start, rows, sizes, trips, tokens = i + 1, [], [], [], 0
        trim_memory()

    from pyspark.sql import types as T

    more = [T.StructField(ids_col, T.ArrayType(T.IntegerType())), T.StructField(size_col, T.IntegerType()), *([T.StructField(check_col, T.BooleanType())] if check else [])]
    return docs.mapInArrow(run, T.StructType([*docs.schema.fields, *more]))


def decode_ids(rows: DataFrame, path: str = MODEL, ids_col: str = "ids", out_col: str = "decoded") -> DataFrame:
    """rows with decoded string behind its own columns; a column of that name is an error."""
    from pyspark.sql import types as T

    _free(rows, [out_col])
    shared = rows.sparkSession.sparkContext.broadcast(load_vocabulary(path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = _codec(shared)
        for b in batches:
            out = [None if x.as_py() is None else codec.decode(x.as_py()) for x in b[ids_col]]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(out, pa.string())], [*b.schema.names, out_col])

    return rows.mapInArrow(run, T.StructType([*rows.schema.fields, T.StructField(out_col, T.StringType())]))


def query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    docs = columns(table(spark, sf_dir, "documents"), doc_id="doc_id", text="text")
    return encode_texts(docs, check=True).select("doc_id", "n_tokens", "ids", "round_trip")
