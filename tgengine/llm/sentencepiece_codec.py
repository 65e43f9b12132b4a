"""SentencePiece encoding and decoding through a table of distinct chunks.

No piece of the vocabulary joins a letter to a following word marker, so no merge crosses the start of a marked word: a
text's ids are those of its marked words, one after another. The corpus's distinct marked words are counted; the most frequent
ones (`HEAD` at most, none longer than `LONGEST` characters, so that their size is bounded) are one table for all tasks, in which
the library has segmented each once. The rare others stay with the task that meets them: it keeps a table of its own for them
(`OWN` entries at most, emptied when full) and segments each new one. Results are put together by position. Joining the rare
ones by shuffle instead moves more than the texts themselves (figures in the README).

A vocabulary that breaks the condition is refused, and so is a normaliser that changes what it should leave alone: besides the
word marks, the library must read a probe of awkward characters as they stand.

Null and empty texts have no ids and decode to the empty text. Row order, repeats and other columns do not matter.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_rows, read, stored

HEAD = 200_000
LONGEST = 64
#: Distinct chunks that a task collects before it hands on their counts.
FLUSH = 250_000
#: Rare chunks that a task keeps.
OWN = 200_000
#: What a normaliser might change: full-width and composed letters, ligatures, blanks of other kinds, controls.
PROBE = "Ａ é e\u0301 ﬁ ² Ⅳ … \u00a0 \u3000 \u200b \t \n x"
MARK = "▁"
CHUNK = re.compile(" [ ]*[^ ]*")
DIGEST = "n_tokens long, ids_sha256 string, decoded_sha256 string"


def default_model() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def chunks(text: str) -> list[str]:
    """The text's marked words without their first marker; the library adds that one itself."""
    if not text:
        return []
    text = text.replace(MARK, " ")
    if "  " not in text and text[0] != " ":
        return text.split(" ")
    return [c[1:] for c in CHUNK.findall(" " + text)]


def library(model: str):
    """The library with this model, if texts may be segmented by marked words."""
    import sentencepiece

    m = sentencepiece.SentencePieceProcessor(model_file=model)
    if any(re.search(f"[^{MARK}]{MARK}", m.id_to_piece(i)) for i in range(m.vocab_size())):
        raise ValueError("a piece crosses a word marker: the texts can't be segmented by marked words")
    if m.decode(m.encode(PROBE)) != PROBE:
        raise ValueError("the model's normaliser changes texts: they can't be segmented as they stand")
    return m


def segment(m, new: list[str]) -> list[tuple[str, str | None]]:
    """Ids as text, and what the chunk decodes to where that differs from it."""
    if not new:
        return []
    ids = m.encode(new, num_threads=1)
    decoded = m.decode(ids, num_threads=1)
    out = [(",".join(map(str, i)), d if d != c else None) for c, i, d in zip(new, ids, decoded)]
    return [(str(m.piece_to_id(MARK)), None) if c == "" else o for c, o in zip(new, out)]


def chunk_counts(texts: DataFrame) -> DataFrame:
    """chunk, c (occurrences) of every distinct chunk."""

    def count(batches):
        seen: Counter = Counter()
        for b in batches:
            for t in b["text"]:
                seen.update(chunks(t or ""))
            if len(seen) > FLUSH:
                yield {"chunk": list(seen), "c": list(seen.values())}
                seen = Counter()
        yield {"chunk": list(seen), "c": list(seen.values())}

    return map_rows(texts.select("text"), "chunk string, c long", count).groupBy("chunk").agg(F.sum("c").alias("c"))


def chunk_table(texts: DataFrame, model: str, head: int = HEAD) -> dict[str, tuple[str, str | None]]:
    """chunk -> (ids as text, its decoding where that differs) of the chunks whose count reaches the least bound that at most `head` short chunks reach; bounds are powers of two, so few."""

    def code(batches):
        m = library(model)
        for b in batches:
            made = segment(m, b["chunk"])
            yield b | {"ids": [x[0] for x in made], "odd": [x[1] for x in made]}

    short = stored(chunk_counts(texts).filter((F.length("chunk") <= LONGEST) & (F.col("c") > 1)))
    low = F.expr("shiftleft(1L, cast(floor(log2(c)) as int))")
    held, least = 0, None
    for r in sorted(short.groupBy(low.alias("low")).count().collect(), reverse=True):
        held += r["count"]
        if held > head:
            break
        least = r["low"]
    if least is None:
        return {}
    chosen = short.filter(F.col("c") >= least).select("chunk")
    return {r["chunk"]: (r["ids"], r["odd"]) for r in map_rows(chosen, "chunk string, ids string, odd string", code, 4096).collect()}


class OwnTable:
    """The rare chunks that one task has met."""

    def __init__(self, model: str, known: dict, size: int | None = None):
        self.model, self.known, self.size = library(model), known, OWN if size is None else size
        self.held: dict[str, tuple[str, str | None]] = {}

    def learn(self, texts: list[list[str]]) -> dict:
        met = set().union(*texts).difference(self.known)
        new = met.difference(self.held)
        if len(self.held) + len(new) > self.size:
            self.held, new = {}, met
        new = list(new)
        self.held.update(zip(new, segment(self.model, new)))
        return self.held


def put_together(text_chunks: list[str], known: dict, others: dict) -> tuple[str, int, str]:
    """(ids as text, their number, decoded text) of a text's chunks in order."""
    parts = [known[c] if c in known else others[c] for c in text_chunks]
    ids = ",".join([p[0] for p in parts])
    decoded = " ".join([c if p[1] is None else p[1] for c, p in zip(text_chunks, parts)])
    return ids, ids.count(",") + 1 if ids else 0, decoded


def coded(docs: DataFrame, model: str, schema: str, row, head: int = HEAD) -> DataFrame:
    """doc_id and the columns that `row(ids as text, number, decoded)` gives, for every row."""
    sent = docs.sparkSession.sparkContext.broadcast(chunk_table(docs, model, head))

    def run(batches):
        table = OwnTable(model, sent.value)
        for b in batches:
            split = [chunks(t or "") for t in b["text"]]
            others = table.learn(split)
            made = [row(*put_together(c, sent.value, others)) for c in split]
            yield {"doc_id": b["doc_id"]} | {k: [m[k] for m in made] for k in (made[0] if made else {})}

    return map_rows(docs.select("doc_id", "text"), f"doc_id long, {schema}", run)


def _sha(x: str) -> str:
    return hashlib.sha256(x.encode()).hexdigest()


def _digest(ids: str, n: int, decoded: str) -> dict:
    return {"n_tokens": n, "ids_sha256": _sha(ids), "decoded_sha256": _sha(decoded)}


def _ids(ids: str, n: int, decoded: str) -> dict:
    return {"ids": [int(x) for x in ids.split(",")] if ids else [], "decoded": decoded}


def digests(docs: DataFrame, model: str | None = None, head: int = HEAD) -> DataFrame:
    return coded(docs.select("doc_id", "text"), model or default_model(), DIGEST, _digest, head)


def encode(docs: DataFrame, model: str | None = None, head: int = HEAD) -> DataFrame:
    """doc_id, ids array<int>, decoded string."""
    return coded(docs.select("doc_id", "text"), model or default_model(), "ids array<int>, decoded string", _ids, head)


def decode(ids: DataFrame, model: str | None = None) -> DataFrame:
    """doc_id, ids -> doc_id, text: the library's own decoding of whole id lists."""
    path = model or default_model()

    def run(batches):
        import sentencepiece

        m = sentencepiece.SentencePieceProcessor(model_file=path)
        for b in batches:
            yield {"doc_id": b["doc_id"], "text": [m.decode(list(x or [])) for x in b["ids"]]}

    return map_rows(ids.select("doc_id", F.col("ids")), "doc_id long, text string", run)


def op6_sentencepiece(spark, sf_dir: str) -> DataFrame:
    return digests(read(spark, sf_dir, "documents"))
