"""Cross-entropy difference of matched n-gram models.

Two bigram models, of a target part and of the whole collection as background,
share one vocabulary, one set of bigrams and one way of smoothing.  A document's
score is the mean over its tokens of the target's loss less the background's:
the lower, the more it reads like the target.

Counts cover all documents, all words and all bigrams.  What follows a word is a
word or the end of the text, so that a context's counts add up to its own count
and each of its distributions to one.
No task holds the whole model: documents are dealt into blocks, a block asks for
the counts of its distinct words and bigrams, which are added up bucket by bucket,
and gets them back in the order in which it asked.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pqspark.llm.common import BROADCAST_ROWS, Files, fresh_path, lean_batches, matched, partitions, small, stored
from pqspark.llm.shingles import U, mix, words

#: Smoothing: pseudo-counts of a word, and weight of the unigram model in a context.
ALPHA, MU = 0.5, 8.0
#: Tokens of a block.
BLOCK = 2_000_000
#: Hash that stands for the begin of a text in bigrams.
BEGIN = U(0x6265_6769_6E5F_5F5F)
_ANSWERS = "block long, slot int, target binary, all binary, distinct long, sum_target long, sum_all long"


def _shrunk(numbers: np.ndarray) -> bytes:
    """Whole numbers of 8 bytes, compressed: all lowest bytes first, so that those of small numbers are runs of zeros."""
    raw = np.ascontiguousarray(numbers.view(np.uint8).reshape(-1, 8).T).tobytes()
    return len(raw).to_bytes(8, "little") + pa.compress(raw, codec="zstd", asbytes=True)


def _grown(packed: bytes, kind: type = np.int64) -> np.ndarray:
    raw = pa.decompress(packed[8:], int.from_bytes(packed[:8], "little"), codec="zstd", asbytes=True)
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8).reshape(8, -1).T).view(kind).ravel()


def _bucket(key: np.ndarray, buckets: int) -> np.ndarray:
    """By the upper bits, so that sorted keys are sorted by bucket too and their steps are small."""
    return ((key >> U(33)) * U(buckets) >> U(31)).astype(np.int64)


def _asked(block: int, slot: np.ndarray, key: np.ndarray, target: np.ndarray, all_: np.ndarray) -> list[tuple]:
    """Rows (block, slot, steps of the sorted keys, target counts, counts), one for each slot."""
    cut = (np.flatnonzero(np.diff(slot)) + 1).tolist()
    return [(block, int(slot[a]), _shrunk(np.diff(key[a:b], prepend=U(0))), _shrunk(target[a:b]), _shrunk(all_[a:b])) for a, b in zip([0, *cut], [*cut, len(slot)], strict=True) if b > a]


def _block_rows(path: str, buckets: int, block_tokens: int):
    """Writes each block's tokens, by number, to a file of its own, and asks for the counts of its words and bigrams."""

    def rows(batches):
        files, made, held, size = Files(path), 0, [], 0

        def close():
            nonlocal made, size
            block = TaskContext.get().partitionId() << 24 | made
            made, size = made + 1, 0
            ids, flags, n = pa.concat_arrays([h[0] for h in held]), np.concatenate([h[1] for h in held]), np.concatenate([h[2] for h in held])
            hashes = np.concatenate([h[3] for h in held])
            held.clear()
            by_token = np.repeat(flags, n).astype(np.float64)
            word, number = np.unique(mix(hashes), return_inverse=True)
            counts = [np.bincount(number, weights=w, minlength=len(word)).astype(np.int64) for w in (by_token, None)]
            out = [(block, -1, b"", _shrunk(np.array([(flags & (n > 0)).sum()])), _shrunk(np.array([(n > 0).sum()])))]
            out += _asked(block, _bucket(word, buckets), word, *counts)
            first = np.cumsum(n) - n
            before = np.empty_like(number)
            before[1:] = number[:-1]
            before[first[n > 0]] = len(word)
            code, token = np.unique(before * (len(word) + 1) + number, return_inverse=True)
            before, number = code // (len(word) + 1), code % (len(word) + 1)
            key = mix(np.append(word, BEGIN)[before] * U(0xD6E8FEB86659FD93) + word[number]) if len(code) else np.zeros(0, np.uint64)
            order = np.argsort(key)
            key, before, number = key[order], before[order], number[order]
            place = np.empty_like(order)
            place[order] = np.arange(len(order))
            token = place[token]
            counts = [np.bincount(token, weights=w, minlength=len(key)).astype(np.int64) for w in (by_token, None)]
            out += _asked(block, _bucket(key, buckets) + buckets, key, *counts)
            columns = [pa.ListArray.from_arrays(pa.array([0, len(ids)], pa.int32()), ids), *(pa.array([_shrunk(c.astype(np.int64))], pa.binary()) for c in (n, token, before, number))]
            whole = pa.RecordBatch.from_arrays(columns, names=["doc_id", "n", "token", "before", "number"])
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, whole.schema) as writer:
                writer.write_batch(whole)
            files.write(str(block), [sink.getvalue().to_pybytes()])
            kinds = (pa.int64(), pa.int32(), pa.binary(), pa.binary(), pa.binary())
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names=["block", "slot", "keys", "target", "all"])

        for batch in batches:
            for at in range(0, batch.num_rows, 100):
                part = batch.slice(at, 100)
                hashes, first = words(part.column(1))
                held.append((part.column(0), part.column(2).to_numpy(zero_copy_only=False).astype(bool), np.diff(first), hashes))
                size += len(hashes)
                if size >= block_tokens:
                    yield close()
        if held:
            yield close()

    return rows


def _sum_rows(buckets: int):
    """Adds up each slot's keys over all blocks and answers each block in the order of its keys; rows come sorted by slot.

    The slots of words also tell how many distinct ones they hold and how often
    these come.  Slot -1 passes on which blocks there are and how many texts begin
    in them.
    """

    def answered(slot: int, held: list[tuple]) -> pa.RecordBatch:
        if slot < 0:
            out = [(block, slot, None, None, 0, int(_grown(target)[0]), int(_grown(all_)[0])) for block, _, target, all_ in held]
        else:
            keys = [np.cumsum(_grown(h[1], np.uint64), dtype=np.uint64) for h in held]
            distinct, back = np.unique(np.concatenate(keys), return_inverse=True)
            target, all_ = (np.bincount(back, weights=np.concatenate([_grown(h[c]) for h in held]), minlength=len(distinct)).astype(np.int64) for c in (2, 3))
            known = (len(distinct), int(target.sum()), int(all_.sum())) if slot < buckets else (0, 0, 0)
            out, end = [], 0
            for (block, *_), key in zip(held, keys, strict=True):
                mine = back[end : (end := end + len(key))]
                out.append((block, slot, _shrunk(target[mine]), _shrunk(all_[mine]), *known))
                known = (0, 0, 0)
        kinds = (pa.int64(), pa.int32(), pa.binary(), pa.binary(), pa.int64(), pa.int64(), pa.int64())
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names=["block", "slot", "target", "all", "distinct", "sum_target", "sum_all"])

    def rows(batches):
        held: list[tuple] = []
        at = None
        for batch in batches:
            for block, slot, *packed in zip(*(batch.column(c).to_pylist() for c in range(5)), strict=True):
                if slot != at and held:
                    yield answered(at, held)
                    held = []
                at = slot
                held.append((block, *packed))
        if held:
            yield answered(at, held)

    return rows


def _score_rows(path: str, vocabulary: int, totals: tuple[int, int], begins: tuple[int, int]):
    """Scores of each block's documents from its file and its answers; rows come sorted by block and slot."""

    def rows(batches):
        files = Files(path)

        def scores(block: int, words_: list[tuple], pairs: list[tuple]) -> pa.RecordBatch:
            with files.open(str(block)) as source:
                whole = pa.ipc.open_stream(source.read()).read_next_batch()
            ids, (n, token, before, number) = whole.column(0).flatten(), (_grown(whole.column(c)[0].as_py()) for c in range(1, 5))
            full, mean = np.flatnonzero(n > 0), np.zeros((2, len(n)))
            first = np.cumsum(n) - n
            for m in (0, 1) if len(token) else ():
                counts, both = (np.concatenate([_grown(p[m]) for p in packed]) for packed in (words_, pairs))
                single = (counts + ALPHA) / (totals[m] + begins[m] + ALPHA * (vocabulary + 1))  # words, and as many ends as begins
                loss = -np.log((both + MU * single[number]) / (np.append(counts, begins[m])[before] + MU))
                mean[m, full] = np.add.reduceat(loss[token], first[full]) / n[full]
            return pa.RecordBatch.from_arrays([ids, pa.array(n), pa.array(mean[0]), pa.array(mean[1]), pa.array(mean[0] - mean[1])], names=["doc_id", "n_tokens", "target_loss", "background_loss", "difference"])

        held: tuple[list, list] = ([], [])
        at = None
        for batch in batches:
            for block, is_pair, *packed in zip(*(batch.column(c).to_pylist() for c in range(4)), strict=True):
                if block != at and at is not None:
                    yield scores(at, *held)
                    held = ([], [])
                at = block
                if packed[0] is not None:
                    held[is_pair].append(packed)
        if at is not None:
            yield scores(at, *held)

    return rows


def scored(docs: DataFrame, target_ids: DataFrame, block_tokens: int = BLOCK) -> DataFrame:
    """(doc_id, n_tokens, target_loss, background_loss, difference) of every row of docs.

    target_ids(doc_id) names the target documents.  Tokens are runs of non-space
    bytes after A-Z are lower-cased.  Texts without tokens, null ones too, have
    losses and difference 0.  With no target document the target model is its
    smoothing alone.  Null numbers are background; repeated rows count as often
    as they come; other columns are not read; an empty table gives an empty one.
    """
    spark = docs.sparkSession
    lean_batches(spark)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    ids = stored(target_ids.select(F.col("doc_id").cast("long").alias("doc_id")).filter("doc_id is not null").distinct().withColumn("target", F.lit(True)), "target")
    flagged = matched(texts, ids, "doc_id", "left").select("doc_id", "text", F.coalesce("target", F.lit(False)).alias("target"))
    if not small(ids, BROADCAST_ROWS):
        flagged = stored(flagged, "flagged")  # a block that is made again must hold the same rows
    n = partitions(spark)
    buckets, path = 4 * n, fresh_path(spark, "blocks")
    asked = flagged.mapInArrow(_block_rows(path, buckets, block_tokens), "block long, slot int, keys binary, target binary, all binary")
    answers = stored(asked.repartition(n, "slot").sortWithinPartitions("slot").mapInArrow(_sum_rows(buckets), _ANSWERS), "answers")
    of = {r.known: r for r in answers.groupBy((F.col("slot") >= 0).alias("known")).agg(F.sum("distinct").alias("n"), F.sum("sum_target").alias("t"), F.sum("sum_all").alias("a")).collect()}
    vocabulary, *totals = (of[True].n, of[True].t, of[True].a) if True in of else (0, 0, 0)
    begins = (of[False].t, of[False].a) if False in of else (0, 0)
    back = answers.repartition(n, "block").sortWithinPartitions("block", "slot").select("block", (F.col("slot") >= buckets).cast("int").alias("pair"), "target", "all")
    return back.mapInArrow(_score_rows(path, vocabulary, tuple(totals), begins), "doc_id long, n_tokens long, target_loss double, background_loss double, difference double")


#: The same from plain counts; losses to six digits.
ORACLE = f"""
WITH l AS (SELECT DISTINCT doc_id, true AS good FROM labels WHERE quality = 1 AND toxic = 0),
d AS (SELECT doc_id, coalesce(good, false) AS good, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') AS ws FROM documents LEFT JOIN l USING (doc_id)),
t AS (SELECT doc_id, good, unnest(ws) AS w, unnest(list_prepend('', ws[1:len(ws) - 1])) AS h FROM d),
s AS (SELECT w, count(*) AS a, count(*) FILTER (good) AS g FROM t GROUP BY 1),
p AS (SELECT h, w, count(*) AS a, count(*) FILTER (good) AS g FROM t GROUP BY 1, 2),
b AS (SELECT count(*) AS a, count(*) FILTER (good) AS g FROM d WHERE len(ws) > 0),
c AS (SELECT w AS h, a, g FROM s UNION ALL SELECT '', a, g FROM b),
n AS (SELECT coalesce(sum(s.a), 0) + any_value(b.a) + {ALPHA}::DOUBLE * (count(s.w) + 1) AS a, coalesce(sum(s.g), 0) + any_value(b.g) + {ALPHA}::DOUBLE * (count(s.w) + 1) AS g FROM b LEFT JOIN s ON true),
q AS (SELECT p.h, p.w, -ln((p.a + {MU} * (s.a + {ALPHA}) / n.a) / (c.a + {MU})) AS a, -ln((p.g + {MU} * (s.g + {ALPHA}) / n.g) / (c.g + {MU})) AS g FROM p JOIN s ON p.w = s.w JOIN c ON p.h = c.h, n),
o AS (SELECT doc_id, count(*) AS n_tokens, avg(q.g) AS g, avg(q.a) AS a FROM t JOIN q ON t.h = q.h AND t.w = q.w GROUP BY 1)
SELECT doc_id, coalesce(n_tokens, 0) AS n_tokens, round(coalesce(g, 0), 6) AS target_loss, round(coalesce(a, 0), 6) AS background_loss, round(coalesce(g - a, 0), 6) AS difference
FROM d LEFT JOIN o USING (doc_id)
"""
