"""Packing documents into fixed-length sequences by exact complements, then best fit.

Only lengths decide a packing, and there are at most `capacity` of them, so the
plan is made from the histogram of piece lengths, whatever the number of rows:
patterns (how many pieces of which lengths share a sequence) with multiplicities.
Piece ranks within a length are then looked up in the pattern's rank ranges. Ranks
come from counts of (length, salt) cells, so that no length, however common, is
numbered in one task.

Defined results: null text is the empty text (the end id alone); null ids are kept
as they are; repeated rows are packed each; an empty table gives no row.
"""

from __future__ import annotations

import zlib
from collections import Counter

from pyspark.sql import DataFrame, Window, functions as F

from pairmatch.llm.common import cut, lean

SALTS = 64
CACHE = 400_000


class ChunkIds(dict):
    """Ids of white-space-free chunks as little-endian bytes, kept up to a bound.

    The tokenizer drops white space, folds case and never merges across white space or
    between letters and other signs, so the ids of a text are those of its chunks in
    turn, and those of a word with marks at its end are the word's and the marks'.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        super().__init__()
        self.tokenizer = Tokenizer.from_file(path)
        self.merges = self.tokenizer.model
        shown = [*range(33, 127), *range(161, 173), *range(174, 256)]  # bytes that stand for themselves; the rest follow from 256 on
        other = {b: 256 + i for i, b in enumerate(x for x in range(256) if x not in shown)}
        self.letters = {c: "".join(chr(other.get(b, b)) for b in chr(c).encode()) for c in range(256)}

    def __missing__(self, chunk: str) -> bytes:
        import numpy as np

        word = chunk.rstrip(".,;:!?")
        if word and word.isalpha() and max(word) < "\u0100" and (word != chunk or not word.islower()):
            return self[word.lower()] + (self[chunk[len(word) :]] if word != chunk else b"")
        if word == chunk and word.isalpha() and word.islower() and max(word) < "\u0100":  # a plain word: straight to the merges
            ids = b"".join([x.id.to_bytes(4, "little") for x in self.merges.tokenize(word.translate(self.letters))])
        else:
            ids = np.asarray(self.tokenizer.encode(chunk, add_special_tokens=False).ids, "<u4").tobytes()
        if len(self) < CACHE and len(chunk) <= 64:
            self[chunk] = ids
        return ids

    def text(self, text: str) -> bytes:
        return b"".join([self[c] for c in text.replace("\n", " ").replace("\t", " ").replace("\r", " ").split(" ")])


_KEPT: dict[str, ChunkIds] = {}


def chunk_ids(path: str) -> ChunkIds:
    """One table a worker process, for all its tasks."""
    if path not in _KEPT:
        _KEPT[path] = ChunkIds(path)
    return _KEPT[path]


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def tokenised_pieces(docs: DataFrame, capacity: int = 2048, path: str | None = None, with_ids: bool = False) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 (and ids) of each document's pieces."""
    path = path or tokenizer_path()
    schema = "doc_id long, piece int, start long, length long, ids_crc32 long" + (", ids array<int>" if with_ids else "")

    def run(batches):
        import numpy as np
        import pyarrow as pa

        table = chunk_ids(path)
        for batch in batches:
            out = []
            ids_col = batch.column(0)
            for i, text in enumerate(batch.column(1)):
                ids = table.text(text.as_py() or "") + b"\0\0\0\0"
                doc_id = ids_col[i].as_py()
                for piece, at in enumerate(range(0, len(ids), 4 * capacity)):
                    part = ids[at : at + 4 * capacity]
                    row = (doc_id, piece, at // 4, len(part) // 4, zlib.crc32(part))
                    out.append(row + ((np.frombuffer(part, "<u4").astype("int32"),) if with_ids else ()))
            cols = list(zip(*out, strict=True)) if out else [[]] * (5 + with_ids)
            types = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int32())]
            names = ["doc_id", "piece", "start", "length", "ids_crc32", "ids"]
            n = 5 + with_ids
            yield pa.record_batch([pa.array(c, t) for c, t in zip(cols, types[:n], strict=True)], names=names[:n])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(lean(run), schema)


def _complement(c, gap: int):
    """One, two or three lengths that sum to the gap, all at hand; largest first."""
    import numpy as np

    if c[gap] > 0:
        return (gap,)

    def pair(g: int, most: int):
        if g < 2:
            return None
        a = np.arange(min(most, g - 1), (g + 1) // 2 - 1, -1)
        ok = (c[a] > 0) & (c[g - a] > (2 * a == g))
        at = int(ok.argmax()) if len(ok) else 0
        return (int(a[at]), int(g - a[at])) if len(ok) and ok[at] else None

    if found := pair(gap, gap):
        return found
    for a in np.flatnonzero(c[: gap - 1] > 0)[::-1]:
        if 3 * a < gap:
            break
        c[a] -= 1
        found = pair(gap - int(a), int(a))
        c[a] += 1
        if found:
            return (int(a), *found)
    return None


def pack_lengths(hist: dict[int, int], capacity: int = 2048) -> list[tuple[dict[int, int], int]]:
    """[(pieces of each length in a sequence, number of such sequences)]."""
    import numpy as np

    c = np.zeros(capacity + 1, np.int64)
    for length, n in hist.items():
        c[length] += n
    plan: list[tuple[dict[int, int], int]] = []

    def take(use: Counter) -> None:
        times = min(int(c[x]) // m for x, m in use.items())
        plan.append((dict(use), times))
        for x, m in use.items():
            c[x] -= m * times

    if c[capacity]:
        take(Counter({capacity: 1}))
    for length in range(capacity - 1, 0, -1):
        while c[length]:
            c[length] -= 1
            found = _complement(c, capacity - length)
            c[length] += 1
            if not found:
                break  # stays for longer combinations and the residuals
            take(Counter((length, *found)))
    while c.any():
        left = c.copy()
        first = int(np.flatnonzero(left)[-1])
        use, gap = Counter({first: 1}), capacity - first
        left[first] -= 1
        while gap:
            if found := _complement(left, gap):
                use.update(found)
                break
            fits = np.flatnonzero(left[: gap + 1])
            if not len(fits):
                break
            use[int(fits[-1])] += 1
            left[fits[-1]] -= 1
            gap -= int(fits[-1])
        take(use)
    return plan


def _ranges(plan, capacity: int):
    """Rank ranges within each length: key, and what a rank there means."""
    import numpy as np

    rows, used, base = [], Counter(), 0
    for use, times in plan:
        at = 0
        for length, m in sorted(use.items(), reverse=True):
            rows.append((length << 44 | used[length], m, base, at, length))
            used[length] += m * times
            at += m * length
        base += times
    rows.sort()
    return tuple(np.array(x, np.int64) for x in zip(*rows, strict=True)) if rows else tuple(np.zeros(0, np.int64) for _ in range(5))


def pack(pieces: DataFrame, capacity: int = 2048) -> DataFrame:
    """Adds sequence_id and offset to pieces (doc_id, piece, ..., length).

    The pieces are read three times: pass a materialised table.
    """
    salted = pieces.withColumn("salt", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(SALTS)).cast("int"))
    cells = salted.groupBy("length", "salt").agg(F.count("*").alias("n"))
    cell_rows = cells.collect()  # at most capacity x SALTS rows
    hist: Counter = Counter()
    begin = {}
    for r in sorted(cell_rows, key=lambda r: (r["length"], r["salt"])):
        begin[r["length"], r["salt"]] = hist[r["length"]]
        hist[r["length"]] += r["n"]
    key, m, base, at, size = _ranges(pack_lengths(hist, capacity), capacity)

    ranked = salted.withColumn("in_cell", F.row_number().over(Window.partitionBy("length", "salt").orderBy("doc_id", "piece")) - 1)
    out_type = pieces.schema.simpleString()[len("struct<") : -1].replace(":", " ") + ", sequence_id bigint, offset bigint"
    names = pieces.columns

    def place(batches):
        import numpy as np

        for pdf in batches:
            first = np.fromiter((begin[x] for x in zip(pdf.length, pdf.salt, strict=True)), np.int64, len(pdf))
            rank = first + pdf.in_cell.to_numpy(np.int64)
            seek = pdf.length.to_numpy(np.int64) << 44 | rank
            r = np.searchsorted(key, seek, side="right") - 1
            k = seek - key[r]
            yield pdf[names].assign(sequence_id=base[r] + k // m[r], offset=at[r] + (k % m[r]) * size[r])

    return ranked.mapInPandas(place, out_type)


def pack_documents(docs: DataFrame, capacity: int = 2048, path: str | None = None) -> DataFrame:
    """Tokenise, cut and pack whole documents."""
    return pack(cut(tokenised_pieces(docs, capacity, path)), capacity)


def fill(packed: DataFrame, capacity: int = 2048) -> DataFrame:
    """One row: sequences used, tokens, the least possible, and the share filled."""
    return packed.agg(F.countDistinct("sequence_id").alias("sequences"), F.sum("length").alias("tokens")).select(
        "sequences", "tokens", F.ceil(F.col("tokens") / capacity).alias("at_least"), (F.col("tokens") / (F.col("sequences") * capacity)).alias("filled")
    )
