"""Token counts of whole texts by a sentencepiece model; huge texts in overlapping chunks that are spliced exactly."""

from __future__ import annotations

from collections.abc import Callable
from functools import lru_cache

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bpe import vocabulary
from .common import by_text

#: Bytes of a chunk and of the overlap at first.
CHUNK, OVERLAP = 262_144, 2_048
Span = tuple[int, int]


@lru_cache(maxsize=2)
def model(path: str):
    import sentencepiece

    return sentencepiece.SentencePieceProcessor(model_file=path)


def spans_of(sp, chunk: bytes, base: int) -> list[Span]:
    """Byte places of the tokens in the whole text; of a character's byte tokens all but the last are empty."""
    return [(base + p.begin, base + p.end) for p in sp.encode(chunk.decode(), return_type="proto").pieces]


def border(data: bytes, at: int) -> int:
    """The character border at or before a byte."""
    while 0 < at < len(data) and data[at] & 0xC0 == 0x80:
        at -= 1
    return min(at, len(data))


def word_start(data: bytes, at: int) -> bool:
    """No piece of the model holds a word mark after another character, so a space after something else always starts a token."""
    return 0 < at < len(data) and data[at] == 0x20 and data[at - 1] != 0x20 and data[at - 3 : at] != "\u2581".encode()


def splice(data: bytes, left: list[Span], right: list[Span], low: int, high: int, agree: int) -> int | None:
    """A place in (low, high) at which the two encodings may be joined, or None.

    Proven places are (1) the start of a word where both encodings have a border, and (2) the end of ``agree`` tokens
    that both encodings have in the same places: every neighbouring pair of the joined sequence then stands in one of
    the two encodings, and neighbouring pairs decide whether a sequence is the merge result.
    """
    starts = {b for b, _ in right if low < b < high}
    common = [b for b, _ in left if b in starts]
    middle = (low + high) // 2
    if words := [p for p in common if word_start(data, p)]:
        return min(words, key=lambda p: abs(p - middle))
    inner = [s for s in left if low < s[0] and s[1] < high]
    both, run = set(inner) & set(right), 0
    for span in inner:
        run = run + 1 if span in both else 0
        if run >= agree and span[1] > span[0] and span[1] in starts:
            return span[1]
    return None


def count_by_chunks(text: str, encode: Callable[[bytes, int], list[Span]], chunk: int = CHUNK, overlap: int = OVERLAP, agree: int = 8) -> int:
    """Tokens of a whole text, read in chunks of bytes; an overlap doubles until it holds a proven place, at worst over all that is left of the chunk, which then grows."""
    data = text.encode()
    total, begin, settled, end = 0, 0, 0, border(data, chunk)
    spans = encode(data[:end], 0)
    while end < len(data):
        width = overlap
        while True:
            low = max(border(data, end - width), settled)
            stop = border(data, low + max(chunk, 2 * (end - low)))
            following = encode(data[low:stop], low)
            at = splice(data, spans, following, low, end, agree)
            if at is not None:
                total += sum(1 for s in spans if s[0] < at)
                begin, settled, end = low, at, stop
                spans = [s for s in following if s[0] >= at]
                break
            if low == settled:
                end = border(data, end + chunk)
                spans = [s for s in encode(data[begin:end], begin) if s[0] >= settled]
                break
            width *= 2
    return total + len(spans)


def token_counts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", name: str = "piece_bpe_32k.model", limit: int = 4096, chunk: int = CHUNK) -> DataFrame:
    """Per row: id, n_bytes (UTF-8), n_tokens of the whole text, over_limit.

    Null texts count as empty: no bytes, no tokens. Texts of up to ``chunk`` bytes are encoded in one go, longer
    ones in overlapping chunks. Repeated rows give repeated results, rows without an id a result without one, an empty table
    gives an empty result; further columns are ignored.
    """

    def counted() -> Callable[[list[str]], list[tuple[int, int]]]:
        sp = model(vocabulary(name))

        def tell(texts: list[str]) -> list[tuple[int, int]]:
            sizes, counts = [len(t.encode()) for t in texts], [0] * len(texts)
            short = [i for i, n in enumerate(sizes) if n <= chunk]
            for i, n in zip(short, map(len, sp.encode([texts[i] for i in short], num_threads=1))):
                counts[i] = n
            for i in set(range(len(texts))) - set(short):
                counts[i] = count_by_chunks(texts[i], lambda part, base: spans_of(sp, part, base), chunk)
            return list(zip(sizes, counts))

        return tell

    return by_text(docs, id_col, text_col, "n_bytes long, n_tokens long", counted).withColumn("over_limit", F.col("n_tokens") > limit)
