"""Token counts: texts are encoded in Arrow batches and only lengths come back.

White space is a safe boundary of every encoding rule used here: no token of the files spans one. Texts are cut there, each
distinct chunk is encoded once by the library in batches of equal bytes, and the result is kept for later texts, so long
texts never reach the encoder in one piece and repeated words cost one look-up.
"""

from __future__ import annotations

import os
import re
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

#: Bytes of text, or of distinct chunks, that one encoding batch holds.
BATCH_BYTES = 4_000_000
#: Chunks that one Python worker remembers at least, once it is full; twice as many at most, about 120 MB.
CACHE_CHUNKS = 300_000

_OTHER_SPACE = re.compile(r"[^\S \n]")
_SAFE = re.compile(r"(?<=\S)(?=[ \n]\S)")


def space_chunks(text: str) -> list[str]:
    """Chunks between spaces and line ends, these left out: for encodings that drop white space."""
    return text.replace("\n", " ").split(" ")


def led_chunks(text: str) -> list[str]:
    """Chunks that begin with the one space or line end before them: for byte-level encodings that keep white space.

    A cut is made only between two characters that are not white space and before a single space or line end, where the
    encoding's own pre-tokeniser always starts a new word; joined again the chunks give the text.
    """
    if not text:
        return []
    if "  " in text or "\n\n" in text or " \n" in text or "\n " in text or text[0] in " \n" or text[-1] in " \n" or _OTHER_SPACE.search(text):
        return _SAFE.split(text)
    head, *rest = text.replace("\n", " \n").split(" ")
    return [head, *[x if x[0] == "\n" else " " + x for x in rest]]


class ChunkEncoder:
    """A bounded memory, in two generations, from chunk to whatever ``pack`` makes of its ids."""

    def __init__(self, path: str, split, pack) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library, self.split, self.pack = Tokenizer.from_file(path), split, pack
        self.library.no_truncation()
        self.library.no_padding()
        self.memory: dict = {}
        self.older: dict = {}

    def encode(self, texts: list[str]) -> Iterator[list]:
        """For each text the packed ids of its chunks, in order."""
        for group in by_bytes(texts):
            cut = [self.split(t) for t in group]
            if len(self.memory) > CACHE_CHUNKS:
                self.older, self.memory = self.memory, {}
            new = [c for c in set().union(*cut) if c not in self.memory]
            older = self.older
            self.memory.update((c, older[c]) for c in new if c in older)
            self.memory.update(self.fresh([c for c in new if c not in older]))
            get = self.memory.__getitem__
            for chunks in cut:
                yield list(map(get, chunks))

    def fresh(self, chunks: list[str]) -> Iterator[tuple]:
        """Chunks not met before, with their packed ids."""
        for batch in by_bytes(chunks):
            yield from zip(batch, map(self.pack, self.library.encode_batch_fast(batch, add_special_tokens=False)), strict=True)


def by_bytes(texts: Iterable[str], most: int = BATCH_BYTES) -> Iterator[list[str]]:
    """Consecutive batches of about ``most`` characters; a longer text is a batch of its own."""
    batch, size = [], 0
    for t in texts:
        if batch and size + len(t) > most:
            yield batch
            batch, size = [], 0
        batch.append(t)
        size += len(t)
    if batch:
        yield batch


def count_tokens(docs: DataFrame, vocabulary: str, limit: int = 2048, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, n_bytes, n_tokens, over_limit`` for every row, whole texts, no special tokens added.

    ``vocabulary`` is the path of a tokenizer file, the same on all executors: ``.json`` is read by tokenizers (cut at
    white space, for encodings that drop it), ``.model`` by sentencepiece (whole texts). Null text is empty: zero bytes and
    tokens. Null or repeated identifiers are passed through, ties and other columns do not matter, an empty table gives
    an empty result.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if vocabulary.endswith(".model"):
            from sentencepiece import SentencePieceProcessor

            pieces = SentencePieceProcessor(model_file=vocabulary)
            lengths = lambda texts: (len(pieces.encode(t, num_threads=1)) for t in texts)
        else:
            encoder = ChunkEncoder(vocabulary, space_chunks, lambda e: len(e.ids))
            lengths = lambda texts: map(sum, encoder.encode(texts))
        for b in batches:
            texts = [t or "" for t in b.column(1).to_pylist()]
            counts = list(lengths(texts))
            n_bytes = [len(t.encode("utf-8", "surrogatepass")) for t in texts]
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array(n_bytes, pa.int64()), pa.array(counts, pa.int64()), pa.array([c > limit for c in counts], pa.bool_())], names=["doc_id", "n_bytes", "n_tokens", "over_limit"]
            )

    rows = docs.selectExpr(f"cast(`{id_col}` as bigint) as doc_id", f"`{text_col}` as text")
    return rows.mapInArrow(run, "doc_id bigint, n_bytes bigint, n_tokens bigint, over_limit boolean")
