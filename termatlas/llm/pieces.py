"""SentencePiece encoding and decoding by a table of distinct marked words (operator 9).

The vocabulary has no piece with a white-space marker after another character, so no
merge reaches across the start of a marked word: a run of markers and what follows up to
the next one. Each task keeps a table of the distinct marked words it has met, segments
a word when it first meets it, and puts the ids back by position. Nothing is shuffled.

A null text counts as empty; the empty text has the begin and end ids only. Rows with
equal keys stay separate rows. Other columns are not read.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import sentencepiece
from pyspark.sql import DataFrame
from termatlas.llm.tables import bounded_batches

MARK = "▁"
#: Entries and characters a task's table holds before it starts anew; results don't depend on them.
TABLE_WORDS, TABLE_CHARS, LONGEST_KEPT = 100_000, 2_000_000, 60


class WordTable:
    """Ids of a text by its marked words."""

    def __init__(self, model: str | bytes, words: int = TABLE_WORDS):
        own = {"model_proto": model} if isinstance(model, bytes) else {"model_file": model}
        self.processor = sentencepiece.SentencePieceProcessor(**own)
        crossing = [p for p in map(self.processor.id_to_piece, range(self.processor.get_piece_size())) if MARK in p.lstrip(MARK)]
        if crossing:
            raise ValueError(f"pieces cross white-space markers: {crossing[:3]}")
        self.words, self.split = words, re.compile(f"{MARK}+[^{MARK}]*").findall
        self.begin, self.end = self.processor.bos_id(), self.processor.eos_id()
        self._restart()

    def _restart(self) -> None:
        self.ids, self.chars = {MARK: [self.processor.piece_to_id(MARK)]}, 0

    def encode(self, text: str) -> list[int]:
        out = [self.begin]
        if text:
            marked = self.split(MARK + text.replace(" ", MARK))
            if len(self.ids) > self.words or self.chars > TABLE_CHARS:
                self._restart()
            new = [w for w in set(marked) if w not in self.ids]
            once: dict[str, list[int]] = {}
            # the library puts one marker in front by itself
            for w, ids in zip(new, self.processor.encode([w[1:] for w in new], num_threads=1), strict=True):
                if len(w) > LONGEST_KEPT:
                    once[w] = ids
                else:
                    self.ids[w] = ids
                    self.chars += len(w)
            known = self.ids
            if once:
                for w in marked:
                    out += known[w] if w in known else once[w]
            else:
                for w in marked:
                    out += known[w]
        out.append(self.end)
        return out


FIELDS = {
    "n_tokens": ("long", pa.int64()),
    "ids": ("array<int>", pa.list_(pa.int32())),
    "decoded": ("string", pa.string()),
    "ids_sha256": ("string", pa.string()),
    "decoded_sha256": ("string", pa.string()),
}


def encode_decode(df: DataFrame, model: str, outputs: tuple[str, ...] = ("n_tokens", "ids", "decoded"), key: str = "doc_id", text: str = "text") -> DataFrame:
    """key and the outputs (names of FIELDS) of each row. model: path of the model file on the executors."""
    kind = df.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = WordTable(model)
        for batch in batches:
            got: dict[str, list] = {name: [] for name in outputs}
            for value in batch.column(1):
                ids = table.encode(value.as_py() or "")
                if "n_tokens" in got:
                    got["n_tokens"].append(len(ids))
                if "ids" in got:
                    got["ids"].append(ids)
                if "ids_sha256" in got:
                    got["ids_sha256"].append(hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest())
                if "decoded" in got or "decoded_sha256" in got:
                    words = table.processor.decode(ids)
                    if "decoded" in got:
                        got["decoded"].append(words)
                    if "decoded_sha256" in got:
                        got["decoded_sha256"].append(hashlib.sha256(words.encode("utf-8", "surrogatepass")).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(got[name], FIELDS[name][1]) for name in outputs)], names=[key, *outputs])

    return bounded_batches(df).select(key, text).mapInArrow(run, f"`{key}` {kind}, " + ", ".join(f"{name} {FIELDS[name][0]}" for name in outputs))
