"""The training-data operators against brute force, round trips and edge cases."""

import hashlib
import io
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from pqspark.llm import ann, html_extract, jaccard_join, line_dedup, lm_scoring, media, packing, page_samples, pfair, shingles, token_tables, toxicity

SF = "/root/testdata/sf0.001"
DOCS = "doc_id long, text string, lang string, source string, n_chars long"
ODD = [(1, None, None, None, None), (2, "", "en", "a", 0), (3, "same words here again", "en", "a", 4), (3, "same words here again", "en", "a", 4), (None, "one two three four five", "en", None, 5), (4, "x " * 5000, "en", "b", 10_000), (5, "SAME words\there  again", "en", "b", 4)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, DOCS)


def _sets(texts, width):
    out = []
    for t in texts:
        w = re.findall("[^\x20\x09-\x0d]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or ""))
        out.append(set() if not w else {tuple(w)} if len(w) < width else {tuple(w[k : k + width]) for k in range(len(w) - width + 1)})
    return out


@pytest.mark.parametrize("width,num,den,block", [(4, 85, 100, 500_000), (5, 4, 5, 500_000), (5, 4, 5, 2_000), (2, 1, 2, 1_000)])
def test_jaccard_components_equal_brute_force(spark, docs, width, num, den, block):
    rows = docs.select("doc_id", "text").collect()
    sets = _sets([r.text for r in rows], width)
    forest = jaccard_join.Forest()
    for a in range(len(rows)):
        for b in range(a):
            both = len(sets[a] & sets[b])
            if both and den * both >= num * (len(sets[a]) + len(sets[b]) - both):
                forest.union(rows[a].doc_id, rows[b].doc_id)
    got = {r.doc_id: r for r in jaccard_join.jaccard_components(docs, width, num, den, block=block).collect()}
    assert all(got[r.doc_id].component_id == forest.find(r.doc_id) and got[r.doc_id].n_shingles == len(s) for r, s in zip(rows, sets, strict=True))


def test_divide_skip_counts():
    rng = np.random.default_rng(3)
    lists = [np.unique(rng.integers(0, 60, n)) for n in (3, 8, 20, 40, 50, 55)]
    counts = np.bincount(np.concatenate(lists), minlength=60)
    for t in range(1, 7):
        found, count = jaccard_join.divide_skip(lists, t)
        assert sorted(found.tolist()) == np.flatnonzero(counts >= t).tolist() and (count == counts[found]).all()


def test_jaccard_edge_cases(spark, odd):
    got = [tuple(r) for r in jaccard_join.jaccard_components(odd, 4, 85, 100).collect()]
    assert sorted(g for g in got if g[0] is not None) == [(1, 0, 1), (2, 0, 2), (3, 1, 3), (3, 1, 3), (4, 1, 4), (5, 1, 3)] and (None, 2, None) in got
    assert sorted(r.doc_id or 0 for r in jaccard_join.one_of_each(odd).collect()) == [0, 1, 2, 3, 4]
    assert jaccard_join.jaccard_components(odd.limit(0)).count() == 0


def test_jaccard_cuts_large_blocks_by_size(spark):
    """Texts of many sizes around one shared passage, with near copies across size levels and a doc_id of two texts."""
    rng = np.random.default_rng(11)
    shared = [f"s{k}" for k in range(60)]
    texts = {}
    for k in range(120):
        own = [f"w{k}x{j}" for j in range(int(rng.integers(20, 400)))]
        texts[2 * k] = [*own, *shared]
        texts[2 * k + 1] = [*own, *shared, *(f"m{k}x{j}" for j in range(int(len(own) * rng.uniform(0, 0.4))))]
    rows = [(k, " ".join(t)) for k, t in texts.items()] + [(0, " ".join(texts[101]))]
    sets = _sets([t for _, t in rows], 5)
    forest = jaccard_join.Forest()
    for a in range(len(rows)):
        for b in range(a):
            both = len(sets[a] & sets[b])
            if 5 * both >= 4 * (len(sets[a]) + len(sets[b]) - both):
                forest.union(a, b)
    groups = defaultdict(list)
    for k in range(len(rows)):
        groups[forest.find(k)].append(rows[k][0])
    want = sorted((d, min(g)) for g in groups.values() for d in g)
    got = jaccard_join.jaccard_components(spark.createDataFrame(rows, "doc_id long, text string").repartition(3), block=400).collect()
    assert sorted((r.doc_id, r.component_id) for r in got) == want


@pytest.mark.parametrize("num,den", [(85, 100), (4, 5), (1, 2)])
def test_similar_sets_share_a_signature_whatever_is_common(num, den):
    rng = np.random.default_rng(5)
    for size in [*range(1, 40), 90, 250, 700]:
        for _ in range(12):
            a = rng.integers(0, 1 << 64, size, np.uint64, endpoint=False)
            differ = int(rng.integers(0, size // 2 + 2))
            b = np.unique(np.r_[a[: size - differ // 2], rng.integers(0, 1 << 64, differ - differ // 2, np.uint64, endpoint=False)])
            a, both = np.unique(a), len(np.intersect1d(a, b))
            if len(a) == both == len(b) or den * both < num * (len(a) + len(b) - both):
                continue
            common = np.sort(rng.choice(np.union1d(a, b), int(rng.integers(0, size + 1)), replace=False)) if rng.random() < 0.8 else None
            parts = shingles.Parts(num, den, common)
            x, y = parts.signatures(a), parts.signatures(b)
            shared = np.intersect1d(x | np.uint64(1), y | np.uint64(1))
            assert len(shared) and np.isin(shared, np.r_[x, y]).any()


def test_shared_passages_tie_few_texts(spark):
    """Texts that differ but for passages which many of them hold are not tied into one block; the same set of texts was before."""
    rng = np.random.default_rng(7)
    pool = [[f"p{k}x{j}" for j in range(40)] for k in range(4)]
    texts = [" ".join(w for part in (pool[rng.integers(4)], [f"w{k}x{j}" for j in range(int(rng.integers(60, 120)))], pool[rng.integers(4)]) for w in part) for k in range(600)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    first = spark.createDataFrame([(shingles.fingerprint(s), k, len(s)) for k, s in enumerate(shingles.shingle_sets(pa.array(texts), 5))], "node long, doc_id long, size long")
    learned = jaccard_join.common_shingles(docs, first, 5)
    assert (np.diff(learned.astype(object)) > 0).all() and len(learned) >= 4 * 36
    blocks = jaccard_join._blocks(docs, 5, 4, 5, common=spark.sparkContext.broadcast(learned))
    assert max([r["count"] for r in blocks.groupBy("root").count().collect()], default=0) <= 30
    assert all(r.component_id == r.doc_id for r in jaccard_join.jaccard_components(docs, 5, 4, 5).collect())


def test_words_agree_over_slices(monkeypatch):
    texts = ["Aa b  Ñc\n" * 50, "", "word", " lead and trail "]
    whole = shingles.words(pa.array(texts))
    monkeypatch.setattr(shingles, "SLICE", 16)
    parts = shingles.words(pa.array(texts))
    assert (whole[0] == parts[0]).all() and whole[1].tolist() == parts[1].tolist() == [0, 150, 150, 151, 154]


def test_token_tables_equal_the_library(spark, docs, odd):
    import public_tokenizers
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    start = 0
    got = {r.doc_id: r for r in token_tables.encoded(docs, shard_rows=60).collect()}
    for r in docs.orderBy("doc_id").collect():
        ids = np.array([*t.encode(r.text or "", add_special_tokens=False).ids, 2], "<u4")
        g = got[r.doc_id]
        assert (g.start, g.n_tokens, g.ids_crc32) == (start, len(ids), zlib.crc32(ids.tobytes()))
        start += len(ids)
    assert token_tables.encoded(odd).count() == len(ODD) and token_tables.encoded(odd.limit(0)).count() == 0
    ids = token_tables.encoder()
    for text in ("a\x1cb   c²½", "don't  stop\n\n ", "日本 <|endoftext|> x", "٣ १ _a__b"):
        assert np.frombuffer(ids(text), "<u2").tolist() == t.encode(text, add_special_tokens=False).ids


def test_token_table_lookups():
    writer, values = token_tables.TableWriter(2), {k * 3: np.arange(k % 7, dtype="<u2") for k in range(-400, 4000)}
    raw = b"".join(c for k in sorted(values) for c in writer.add(token_tables.key_of(k), values[k].tobytes())) + b"".join(writer.finish())
    reader = token_tables.TableReader(io.BytesIO(raw))
    assert all((reader.get(k) == v).all() for k, v in values.items()) and len(reader.blocks) >= 1
    assert all(reader.get(k) is None for k in (1, -7, 99_999_999)) and sum(reader.maybe(k * 3 + 1) for k in range(1000)) < 60


def test_media_round_trip_and_retries(spark, odd, tmp_path, monkeypatch):
    got = [r.asDict() for r in media.digested(odd).collect()]
    assert len(got) == len(ODD)
    for r in got:
        text = {d[0]: d[1] for d in ODD}[r["doc_id"]] or ""
        payload = text.encode().ljust(max(1, -(-len(text.encode()) // 192)) * 192)
        assert (r["n_bytes"], r["payload_sha256"], r["tail_crc32"]) == (len(text.encode()), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]))
    path = str(tmp_path / "archives")
    media.write_archives(odd, path)
    reader = media.ArchiveReader({"path": path, "rangeBytes": "50"})
    failed, member = [], media.ArchiveReader.member
    spans = reader.partitions()

    def flaky(file, offset, size, crc):
        if (offset, size) not in failed:
            failed.append((offset, size))
            raise OSError("lost")
        return member(file, offset, size, crc)

    monkeypatch.setattr(media.ArchiveReader, "member", staticmethod(flaky))
    assert sum(b.num_rows for s in spans for b in reader.read(s)) == len(ODD) and len(spans) > len(ODD) and failed


def test_toxicity_learns_and_spares(spark):
    rows = [(k, ("you are a stupidhead really" if k % 3 == 0 else "a calm and pleasant day") + f" w{k}") for k in range(300)]
    d = spark.createDataFrame(rows, "doc_id long, text string")
    model = toxicity.fit(d, d.selectExpr("doc_id", "cast(doc_id % 3 = 0 as int) AS toxic"))
    got = {r.doc_id: r for r in toxicity.scored(d, model).collect()}
    assert all(got[k].predicted == (k % 3 == 0) for k in range(300)) and got[0].held_out == (zlib.crc32(b"0") % 5 == 0)
    assert toxicity.kept(d, model).count() == 200
    assert toxicity.fit(d, d.limit(0).selectExpr("doc_id", "1 AS toxic")).scorer().score(None) < 0.5


def test_toxicity_keeps_terms_beside_others(spark):
    """Two terms that always come together are both learned; a rare companion is not."""
    rows = [(k, ("some trash and scum here" + " rarely" * (k < 12) if k % 3 == 0 else "some calm day and nice weather here") + f" w{k}") for k in range(600)]
    d = spark.createDataFrame([*rows, (1000, "only scum this time"), (1001, "only trash this time"), (1002, "rarely seen this time")], "doc_id long, text string")
    model = toxicity.fit(d, d.filter("doc_id < 600").selectExpr("doc_id", "cast(doc_id % 3 = 0 as int) AS toxic"))
    got = {r.doc_id: r.predicted for r in toxicity.scored(d, model).collect()}
    assert [got[k] for k in (1000, 1001, 1002)] == [1, 1, 0] and all(got[k] == (k % 3 == 0) for k in range(600))


def test_automaton_equals_edit_distance():
    entries = {"idiot": 1.0, "worthless": 1.0, "bad": 1.0, "vequ~": 1.0}
    a = toxicity.Automaton(entries)

    def edits(x, y):
        row = list(range(len(y) + 1))
        for i, c in enumerate(x, 1):
            new = [i]
            for j, d in enumerate(y, 1):
                new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (c != d)))
            row = new
        return row[-1]

    rng = np.random.default_rng(0)
    for _ in range(800):
        w = list(rng.choice(["idiot", "worthless", "bad"]))
        for _ in range(rng.integers(0, 4)):
            at = rng.integers(0, len(w) + 1)
            w[at : at + rng.integers(0, 2)] = rng.choice(list("abidotz"), rng.integers(0, 2)).tolist()
        w = "".join(w)
        want = min((edits(w, e) for e in ("idiot", "worthless", "bad") if edits(w, e) <= toxicity.distance_for(len(e))), default=None)
        got = a.match(w)
        assert (got[1] if got else None) == want, w
    assert a.match("vequxyz") == ("vequ~", 0)


def test_packing_keeps_rules(spark, docs, odd):
    rows = packing.packed(docs, capacity=256, shard_rows=50).collect()
    source = {r.doc_id: r.source for r in docs.collect()}
    bins, whole = defaultdict(list), defaultdict(int)
    for r in rows:
        bins[r.shard, r.bin].append(r)
        whole[r.doc_id] += r.length
    for held in bins.values():
        held.sort(key=lambda r: r.bin_offset)
        assert sum(r.length for r in held) <= 256 and len({source[r.doc_id] for r in held}) == len(held)
        assert all(a.bin_offset + a.length == b.bin_offset for a, b in zip(held, held[1:], strict=False))
    assert whole == {r.doc_id: len((r.text or "").split()) + 1 for r in docs.collect()}
    assert len(packing.packed(odd).select("doc_id").collect()) == len(ODD) + 2 and packing.packed(odd.limit(0)).count() == 0


def test_packing_takes_the_tightest_compatible_bin():
    got = packing.pack([(6, "a", None, 0), (7, "b", None, 1), (3, "b", None, 2), (2, "b", 9, 3), (1, "c", 9, 4)], 10)
    assert got == [(1, 0), (0, 0), (1, 6), (2, 0), (1, 9)]


def test_pfair_deviation_and_dates(spark):
    weights = spark.createDataFrame([("a", 5), ("b", 3), ("c", 2), ("d", 1)], "source string, parts long")
    plan = {r.source: r for r in pfair.period_plan(weights).collect()}
    assert sorted(x for r in plan.values() for x in r.slots) == list(range(11))
    for r in plan.values():
        for t in range(12):
            assert abs(sum(x < t for x in r.slots) - t * r.parts / 11) < 1
        for k, x in enumerate(r.slots):
            assert k * 11 // r.parts <= x < -(-(k + 1) * 11 // r.parts)


def test_pfair_keeps_all_rows(odd):
    assert pfair.mixed(odd).count() == pfair.interleaved(odd).count() == len(ODD)
    assert pfair.mixed(odd.limit(0)).count() == 0


def test_pfair_gives_every_source_its_slots(spark):
    """More sources than the shortest period has slots, one of them large."""
    rows = spark.range(1200).selectExpr("id as doc_id", "cast(id as string) as source").unionByName(spark.range(40_000).selectExpr("id + 10000 as doc_id", "'hot' as source"))
    got = pfair.mixed(rows).collect()
    assert len(got) == 41_200 and all(r.slot is not None and r.release <= r.slot < r.due for r in got)
    assert len({r.slot for r in got}) == len({(r.source, r.block) for r in got})
    parts = {r.source: r.parts for r in pfair.tempered(rows, F.col("source")).collect()}
    assert sum(parts.values()) == 12_010 and len(parts) == 1201 and parts["hot"] > 100 * max(v for k, v in parts.items() if k != "hot")


def test_line_dedup_edges(spark, odd):
    got = line_dedup.without_boilerplate(odd).collect()
    assert len(got) == len(ODD) and {r.doc_id: (r.n_lines, r.text) for r in got}[1] == (0, None)
    d = spark.createDataFrame([(k, f"menu\nown {k}\n\nmenu", "s") for k in range(20)], "doc_id long, text string, source string")
    assert {r.text for r in line_dedup.without_boilerplate(d).collect()} == {f"own {k}\n" for k in range(20)}
    assert line_dedup.without_boilerplate(odd.limit(0)).count() == 0


def test_neighbours_recall_and_edges(spark):
    rng = np.random.default_rng(5)
    x = rng.normal(size=(3000, 24))
    x[100:140] = x[100]
    rows = [(k, v.tolist()) for k, v in enumerate(x)] + [(5000, None), (5001, [0.0] * 24), (5002, [float("nan")] * 24), (5003, [None] * 24), (5004, [])]
    got = defaultdict(list)
    for r in ann.neighbours(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), F.col("vec_id") % 50 == 0).orderBy("query_id", "rank").collect():
        got[r.query_id].append((r.vec_id, r.score))
    unit = x / np.sqrt((x * x).sum(1))[:, None]
    hits = 0
    for q in range(0, 3000, 50):
        s = unit @ unit[q]
        s[q] = -9
        hits += len({v for v, _ in got[q]} & set(np.lexsort((np.arange(3000), -np.round(s, 12)))[:5].tolist()))
    assert hits / 300 >= 0.9 and [v for v, _ in got[100]] == [101, 102, 103, 104, 105] and len(got) == 60


@pytest.mark.parametrize("n,few", [(4, 512), (51, 512), (700, 512)])
def test_neighbours_are_never_short(spark, n, few):
    """Few rows, and many that lie far from each other, with few probes: as many answers as there are rows, five at most; exact where few."""
    x = np.random.default_rng(n).normal(size=(n, 64))
    d = spark.createDataFrame([(k, v.tolist()) for k, v in enumerate(x)], "vec_id long, embedding array<double>").coalesce(1)
    got = defaultdict(list)
    for r in ann.neighbours(d, F.col("vec_id") % 3 == 0, tables=1, probes=1).orderBy("query_id", "rank").collect():
        got[r.query_id].append(r.vec_id)
    unit = x / np.sqrt((x * x).sum(1))[:, None]
    for q in range(0, n, 3):
        s = unit @ unit[q]
        assert len(got[q]) == min(5, n - 1) and q not in got[q]
        if n < few:
            assert got[q] == [v for v in np.argsort(-s) if v != q][:5]


def test_extraction_on_held_out_layouts():
    field, wrong, n = html_extract.standard_field(), 0, 0
    for page, labels in page_samples.labelled_pages(80, seed=77):
        wrong += sum(a != b for a, b in zip(field.decode(page), labels, strict=True))
        n += len(labels)
    assert wrong / n < 0.01
    html = '<nav><a href=x>Home</a></nav><article><h1>Title &amp; more</h1><p><b>One\n two.<br><p>Three four.</article><footer>&copy; x</footer>'
    assert html_extract.main_text(html, field) == "Title & more\n\nOne two.\n\nThree four." and html_extract.main_text(None, field) == ""


def test_viterbi_is_the_best_path():
    rng = np.random.default_rng(2)
    page = page_samples.labelled_pages(1, 5)[0][0][:9]
    field = html_extract.Field(rng.normal(size=(len(html_extract.NAMES), 2)), rng.normal(size=(2, 2)))
    s = [field.state[f].sum(axis=0) for f in html_extract.features(page)]
    score = lambda y: sum(s[k][v] for k, v in enumerate(y)) + sum(field.step[a][b] for a, b in zip(y, y[1:], strict=False))
    paths = [[m >> k & 1 for k in range(len(page))] for m in range(1 << len(page))]
    assert field.decode(page) == max(paths, key=score)


def test_lm_scoring_counts(spark, odd):
    d = spark.createDataFrame([(1, "a b a b"), (2, "c d"), (3, None)], "doc_id long, text string")
    got = {r.doc_id: r for r in lm_scoring.scored(d, d.filter("doc_id = 1")).collect()}
    assert got[1].n_tokens == 4 and got[1].difference < 0 < got[2].difference and got[3].difference == 0
    # by hand: c in document 2 after the begin mark, 1 of 2 documents; unigram (1 + .5) / (6 words + 2 ends + .5 * 5)
    p = lambda pair, before, c: (pair + 8 * (c + 0.5) / 10.5) / (before + 8)
    assert abs(got[2].background_loss + (np.log(p(1, 2, 1)) + np.log(p(1, 1, 1))) / 2) < 1e-9
    assert lm_scoring.scored(odd, odd.limit(0).select("doc_id")).count() == len(ODD) and lm_scoring.scored(odd.limit(0), odd.select("doc_id")).count() == 0


def test_lm_scoring_keeps_all_words_and_bigrams(spark, docs):
    """Losses by plain counting, on more words than any fixed vocabulary of 8192 holds; several blocks."""
    rows = docs.select("doc_id", "text").collect()
    tokens = {r.doc_id: re.findall("[^\x20\x09-\x0d]+", re.sub("[A-Z]", lambda m: m.group().lower(), r.text or "")) for r in rows}
    tokens |= {1000 + k: [f"own{k}x{j}" for j in range(200)] * 2 for k in range(60)}
    good = {d for d in tokens if d % 3 == 0}
    single, pairs, begins = (Counter(), Counter()), (Counter(), Counter()), [0, 0]
    for d, t in tokens.items():
        for m in (0, 1) if d in good else (1,):
            single[m].update(t)
            pairs[m].update(zip([None, *t], t, strict=False))
            begins[m] += bool(t)
    assert len(single[1]) > 8192
    every = spark.createDataFrame([(r.doc_id, r.text) for r in rows] + [(d, " ".join(t)) for d, t in tokens.items() if d >= 1000], "doc_id long, text string").repartition(3)
    got = {r.doc_id: r for r in lm_scoring.scored(every, spark.createDataFrame([(d,) for d in good], "doc_id long"), block_tokens=5000).collect()}
    assert got.keys() == tokens.keys()
    total = [sum(single[m].values()) + begins[m] + 0.5 * (len(single[1]) + 1) for m in (0, 1)]

    def chance(m, a, b, both):
        return (both + 8 * (single[m][b] + 0.5) / total[m]) / ((begins[m] if a is None else single[m][a]) + 8)

    for d, t in tokens.items():
        for m, loss in ((0, got[d].target_loss), (1, got[d].background_loss)):
            want = -sum(np.log(chance(m, a, b, pairs[m][a, b])) for a, b in zip([None, *t], t, strict=False))
            assert abs(loss - want / max(1, len(t))) < 1e-9 and got[d].n_tokens == len(t)
    # each context's distribution over all words and the end of the text adds up to one, in both models
    ends = [Counter(t[-1] for d, t in tokens.items() if t and (m or d in good)) for m in (0, 1)]
    for m in (0, 1):
        for a in [None, *list(single[1])[:20]]:
            mass = sum(chance(m, a, b, pairs[m][a, b]) for b in single[1])
            mass += (ends[m][a] + 8 * (begins[m] + 0.5) / total[m]) / ((begins[m] if a is None else single[m][a]) + 8)
            assert abs(mass - 1) < 1e-9


def test_pipeline_stages(spark):
    pipeline = pytest.importorskip("corpus_pipeline")
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns = docs.columns
    before = {r.doc_id: r for r in docs.collect()}
    clean = pipeline.drop_toxic(spark, docs, SF)
    labels = spark.read.parquet(f"{SF}/labels.parquet").filter("toxic = 0").select("doc_id")
    lost = docs.join(labels, "doc_id").select("doc_id").subtract(clean.select("doc_id")).count()
    assert lost <= 1 and clean.count() < len(before)
    lines = pipeline.drop_lines(spark, clean, SF)
    assert lines.columns == columns and lines.count() == clean.count()
    assert all(set((r.text or "").split("\n")) <= set((before[r.doc_id].text or "").split("\n")) | {""} and r.n_chars == len(r.text) for r in lines.collect())
    one = pipeline.drop_near_duplicates(spark, lines, SF)
    rows = lines.select("doc_id", "text").collect()
    sets, forest = _sets([r.text for r in rows], 5), jaccard_join.Forest()
    for a in range(len(rows)):
        for b in range(a):
            both = len(sets[a] & sets[b])
            if both and 5 * both >= 4 * (len(sets[a]) + len(sets[b]) - both):
                forest.union(rows[a].doc_id, rows[b].doc_id)
    assert sorted(r.doc_id for r in one.collect()) == sorted({forest.find(r.doc_id) for r in rows})
    mixed = pipeline.mix_sources(spark, one, SF)
    assert mixed.columns == columns and mixed.count() == one.count()
    assert pipeline.run(spark, SF).select("doc_id").distinct().count() == one.count()
