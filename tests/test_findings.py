"""Small tests of faults that were found on odd inputs and larger tables."""

import datetime
import os
import tracemalloc

import duckdb
import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import functions as F

import corpus_pipeline
from pqspark import catalog, workloads
from pqspark.functions import kernels
from pqspark.llm import jaccard_join, packing, shingles
from pqspark.model import PQModel
from pqspark.operators import encode, index, search, train, vectors


def _copy(spark, folder, **tables) -> str:
    for name, df in tables.items():
        df.write.mode("overwrite").parquet(f"{folder}/{name}.parquet")
    return str(folder)


def test_means_of_users_are_exact(spark, tmp_path):
    """(0.1 + 0.2 + 0.3 + ...) / 16 lies at a tie of the sixth place, where the order of a sum of doubles would tell."""
    values = [0.1, 0.2, 0.3, 0.4, 0.7, 1.1, 55.55, 1e6, 0.6, 0.01, 0.02, 3.3, 4.7, 0.05, 77.77, 0.04]
    want = round(float(sum(round(v * 100) for v in values)) / 1600, 9)
    for k, order in enumerate((values, values[::-1], sorted(values))):
        rows = [(7, datetime.datetime(2024, 1, 1), "a", v) for v in order]
        d = _copy(spark, tmp_path / str(k), events=spark.createDataFrame(rows, "user_id long, ts timestamp, event_type string, value double").coalesce(1))
        assert vectors.user_hours(spark, d).first().embedding[-3] == want
    odd = [(7, datetime.datetime(2024, 1, 1), "a", v) for v in (1e300, 1e-12, None)]
    d = _copy(spark, tmp_path / "odd", events=spark.createDataFrame(odd, "user_id long, ts timestamp, event_type string, value double"))
    assert vectors.user_hours(spark, d).first().embedding[-3] == 5e299


def test_drift_waits_for_the_whole_span(spark, tmp_path):
    """Ids of more than ten years of hours: no row is late."""
    e = vectors.table(spark, "/root/testdata/sf0.001", "embeddings")
    wide = e.withColumn("vec_id", F.when(F.col("vec_id") < 16, F.col("vec_id")).otherwise(F.col("vec_id") * 10_000))
    d = _copy(spark, tmp_path, embeddings=wide)
    made = catalog.queries()["stream_drift"](spark, d)
    assert made.agg(F.sum("n")).first()[0] == wide.count() and made.count() == wide.selectExpr("vec_id div 24").distinct().count()


def test_packing_follows_the_mix(spark):
    docs = spark.createDataFrame([(k, f"w{k} " * (1 + k % 7), "abc"[k % 3 if k < 900 else 0]) for k in range(1500)], "doc_id long, text string, source string")
    mix = corpus_pipeline.mix_sources(spark, docs, "").persist()
    assert mix.count() == 1500
    both = packing.packed(mix, shard_rows=300, order=corpus_pipeline.PLACES).join(mix, "doc_id").groupBy("shard").agg(F.min("mix_slot"), F.max("mix_slot"), F.count("*")).orderBy("shard").collect()
    assert len(both) >= 4 and sum(r[3] for r in both) == 1500 and all(r[3] <= 600 for r in both)
    assert all(a[2] < b[1] for a, b in zip(both, both[1:]))
    turned = mix.withColumn("mix_slot", F.lit(1_000_000) - F.col("mix_slot"))
    places = lambda df: {(r.doc_id, r.shard, r.bin) for r in corpus_pipeline.pack_sequences(spark, df, "").collect()}
    assert places(mix) != places(turned)
    nulls = spark.createDataFrame([(1, "a", None, None, None), (None, None, "x", 3, 1)], "doc_id long, text string, source string, mix_slot long, mix_row int")
    assert corpus_pipeline.pack_sequences(spark, nulls, "").count() == 2 and corpus_pipeline.pack_sequences(spark, nulls.limit(0), "").count() == 0


def test_measures_come_from_the_table(spark, tmp_path):
    """Vectors of 20 and of 40 dimensions give other sizes, lanes and working sets than the given ones of 64."""
    rows = [(k, [float(k + j) for j in range(20 if k < 8 else 40)], 0) for k in range(24)]
    d = _copy(spark, tmp_path, embeddings=spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int"))
    run = lambda name: catalog.queries()[name](spark, d)
    assert {(r.width, r.dim): (r.bytes, r.table_bytes) for r in run("sizes").collect()}[16, 40] == (3, 48)
    # 8 rows of 20 dimensions in pieces of 16 and 4 (two rounds of 16 lanes), 16 rows of 40 in 16, 16 and 8 (three)
    lanes = {r.width: (r.by_dimension, r.by_centroid) for r in run("lane_utilisation").collect()}
    assert lanes[16] == ((8 * 20 + 16 * 40) / (8 * 32 + 16 * 48), 24 / 32)
    assert {r.width: r.bytes for r in run("working_set").collect()}[32] == 4 * 24 * 32 + 4 * 24
    assert {r.value for r in run("cost_model").filter("strategy = 'staged' AND counter = 'arithmetic'").collect()} == {24 * 256 * (2 * 40 - 4) + 24 * 4 * 256}
    assert {r.value for r in run("cost_model_all").filter("strategy = 'staged' AND counter = 'bytes_in'").collect()} == {4 * 24 * 40}
    w10 = {(r.params["dim"], r.metric): r.value for r in run("w10_defaults").collect()}
    assert w10["80", "table_bytes"] == 2 * 5 and w10["160", "bytes"] == 10


def test_tuning_holds_no_long_lists(spark, monkeypatch):
    """The candidates needed are those that tune finds, and no task keeps more of a query than its true neighbours."""
    d = "/root/testdata/sf0.001"
    e, model = catalog.rows(spark, d), catalog.first_k(spark, d)
    q, codes, truth = catalog.queries_of(e), encode.encode(e, model), search.exact(catalog.queries_of(e), e).persist()
    want = search.tune(lambda l: search.adc(q, codes, model, l), truth, 10, 0.95)
    far = search.adc(q, codes, model, 10_000).select("query_id", "vec_id", "rank").join(truth.drop("rank"), ["query_id", "vec_id"]).select("query_id", "vec_id", "rank")
    assert set(search.adc_ranks(q, codes, model, truth).collect()) == set(far.collect())
    made = search._Top.__init__

    def short(self, q_ids, k, skip_self):
        assert k <= 10
        made(self, q_ids, k, skip_self)

    monkeypatch.setattr(search._Top, "__init__", short)
    kept = []
    monkeypatch.setattr(search, "adc", lambda *a, **b: kept.append(a))
    assert catalog.queries()["tune_candidates"](spark, d).first()[0] == want and not kept


def test_pruning_equals_the_plain_loop():
    rng = np.random.default_rng(2)
    x = np.round(rng.normal(size=(90, 6)), 1)
    x[40:50] = x[7]
    for n in (0, 1, 5, 24, 25, 80):
        for alpha, degree in ((1.0, 4), (1.2, 16), (3.0, 60)):
            point = int(rng.integers(90))
            candidates = [(float(((x[c] - x[point]) ** 2).sum()), c) for c in rng.choice(90, n, replace=False).tolist()]
            kept: list[int] = []
            for dist, c in sorted(candidates):
                if c != point and len(kept) < degree and all(alpha * ((x[k] - x[c]) ** 2).sum() > dist for k in kept):
                    kept.append(c)
            assert index.pruned(x, point, candidates, degree, alpha) == kept


def test_beam_search_builds_the_graph_once(spark, tmp_path):
    e = vectors.collection("emb64", spark, "/root/testdata/sf0.001").select("vec_id", "embedding").filter("vec_id < 120")
    told = str(tmp_path / "built")

    def build(batches):
        for batch in batches:
            with open(told, "a") as out:
                out.write("x" * batch.num_rows)
            yield batch

    model = train.lloyd(e, catalog.config(width=16, iterations=1, k=8))
    graph = index.build_graph(e, 8, 16).coalesce(1).mapInArrow(build, "vec_id long, neighbors array<long>, dists array<float>")
    found = index.beam(e.filter("vec_id % 20 = 0"), graph, encode.encode(e, model), model, e, [0, 1], width=16, k=3).collect()
    assert len(found) == 18 and len(open(told).read()) == 120


def test_index_time_builds_the_graph_once(spark, monkeypatch):
    calls = []
    monkeypatch.setattr(index, "build", lambda df, config, graph=True: calls.append(graph) or (None, None, None, {"train": 1.0, "encode": 2.0, "graph": 7.0 if graph else 0.0}))
    got = workloads.w1_index_time(spark, "/root/testdata/sf0.001").collect()
    assert calls == [True, False, False, False]
    assert [r.value for r in got if r.metric == "graph_s"] == [7.0] * 4 and [r.value for r in got if r.metric == "share"] == [0.3] * 4


def test_checks_keep_similar_sets_and_part_chance_agreements():
    """Similar sets share a signature with near checks; texts with passages in common, none known as common, are not tied into one block."""
    rng = np.random.default_rng(17)
    draw = lambda n: rng.integers(0, 1 << 64, n, np.uint64, endpoint=False)
    for num, den in ((85, 100), (4, 5), (1, 2)):
        parts, tried = shingles.Parts(num, den), 0
        for size in [*range(1, 40), 90, 250, 700] * 10:
            a = np.unique(draw(size))
            lost, new = rng.integers(0, size * (den - num) // den + 1, 2)
            b = np.unique(np.r_[rng.permutation(a)[: size - lost], draw(new)])
            both = len(np.intersect1d(a, b))
            if len(a) == both == len(b) or den * both < num * (len(a) + len(b) - both):
                continue
            tried += 1
            rows = [(*parts.checked(x), np.full(len(parts.signatures(x)), k)) for k, x in enumerate((a, b))]
            assert len(jaccard_join._alike(*(np.concatenate(c) for c in zip(*rows)))[0])
        assert tried > 20

    pool = [[f"p{k}x{j}" for j in range(40)] for k in range(4)]
    texts = [" ".join(w for part in (pool[rng.integers(4)], [f"w{k}x{j}" for j in range(int(rng.integers(100, 160)))], pool[rng.integers(4)]) for w in part) for k in range(600)]
    made = jaccard_join._signature_rows(5, 4, 5, 1)(iter(pa.table({"text": texts}).to_batches(max_chunksize=100)))
    forest = jaccard_join.Forest()
    for one in jaccard_join._tied_rows(made):
        jaccard_join._tie(forest, one.column(0).to_numpy(), one.column(1).to_numpy())
    assert np.unique(np.r_[0, forest.edges()[1]], return_counts=True)[1].max() <= 30


def test_many_checks_of_one_signature_tie_all(monkeypatch):
    sig, check, node = np.full(9, 0x51 | 7 << 1, np.uint64), (np.uint64(1) << np.arange(9, dtype=np.uint64) * np.uint64(7)) * np.uint64(255), np.arange(9)
    assert not len(jaccard_join._alike(sig & ~np.uint64(1), check, node)[0])
    assert len(jaccard_join._alike(sig, check, node)[0]) < 36
    monkeypatch.setattr(jaccard_join, "MANY", 8)
    u, v = jaccard_join._alike(sig, check, node)
    assert set(np.r_[u, v]) == set(range(9)) and len(set(v)) == 1


def test_measures_encode_no_more_than_needed(spark, monkeypatch):
    """A variant encodes once to be compared and three times to be timed; training keeps no second copy of what is in memory."""
    df = vectors.collection("emb64", spark, "/root/testdata/sf0.001").select("vec_id", "embedding").persist()
    df.count()
    held = lambda: spark.sparkContext._jsc.getPersistentRDDs().size()
    before, seen = held(), []
    model = train.lloyd(df, catalog.config(width=16, iterations=2, k=8), on_iteration=lambda *_: seen.append(held()))
    assert seen == [before, before] and held() == before and df.storageLevel.useMemory
    assert model.diff(train.lloyd(df.select("*"), catalog.config(width=16, iterations=2, k=8))) == 0
    made, calls = encode.encode, []
    monkeypatch.setattr(encode, "encode", lambda *a, **b: calls.append(a[2] if len(a) > 2 else "wanted") or made(*a, **b))
    got = workloads._measure("w", df, catalog.config(width=16, iterations=1, k=8), {"matrix": ("matrix", {})}, {})
    assert calls == ["wanted"] + ["matrix"] * 4
    assert [m[2] for m in got].count("encode_s") == 3 and {m[2]: m[3] for m in got}["agreement"] == 1
    df.unpersist()


def _profiles(spark, d) -> tuple[dict, dict]:
    """Profiles of customers by the query, and by its SQL on one thread, which takes rows in the tables' order."""
    con = duckdb.connect()
    con.execute("SET threads = 1")
    for t in ("orders", "lineitem"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{d}/{t}.parquet{'/*.parquet' if os.path.isdir(f'{d}/{t}.parquet') else ''}'")
    got = {r.vec_id: r.embedding for r in catalog.queries()["cust_profile"](spark, str(d)).collect()}
    return got, dict(con.execute(f"SELECT vec_id, embedding FROM ({catalog.oracle_sql()['cust_profile']})").fetchall())


def _write(path, columns: dict, *names: str, per_file=10**9) -> None:
    os.makedirs(path)
    table = pa.table(columns)
    for k, name in enumerate(names):
        pq.write_table(table.slice(k * per_file, per_file if k < len(names) - 1 else None), f"{path}/{name}.parquet")


def test_customers_sum_in_the_order_of_the_tables(spark, tmp_path):
    """1e16 - 1e16 + 1 is 1 in this order alone; Spark takes the last file first, as the largest. Order 3 has no lines, order 4 no price, order 5 no customer."""
    day = datetime.datetime(2024, 3, 1)
    big = [1e16, -1e16, 1.0]
    lines = {"l_orderkey": [1] * 3 + [2] * 5000 + [4, None], "l_quantity": [*big, *([2.0] * 5000), None, 9.0], "l_discount": [*big, *(float(k) for k in range(5000)), None, 9.0]}
    _write(tmp_path / "lineitem.parquet", lines, "a", "b", "c", per_file=1)
    orders = {"o_orderkey": [10, 11, 1, 2, 3, 4, 5], "o_custkey": [7, 7, 7, 8, 9, 6, None], "o_totalprice": [*big, 4.0, 5.0, None, 6.0], "o_orderdate": [day] * 6 + [None]}
    _write(tmp_path / "orders.parquet", orders, "a", "b", "c", per_file=1)
    got, want = _profiles(spark, tmp_path)
    assert got == want and set(got) == {6, 7, 8, 9, None}
    assert got[7][12:] == [0.333333, 0.333333, 0.333333, 3.0] and got[6][12:] == [None, None, None, 1.0] and got[9][12:] == [5.0, 0.0, 0.0, 0.0]


def test_customers_round_as_their_sql_does(spark, tmp_path):
    """A mean whose digits lie at a tie of the sixth place: times 10^6 it may lie below; not finite and very large ones stay."""
    means = [(2 * k + 1) / 2e6 for k in range(0, 90_000, 37)] + [-0.0000015, 1e300, 1e305, float("inf"), float("nan"), None]
    keys = list(range(len(means)))
    _write(tmp_path / "lineitem.parquet", {"l_orderkey": keys, "l_quantity": [1.0] * len(keys), "l_discount": means}, "a")
    _write(tmp_path / "orders.parquet", {"o_orderkey": keys, "o_custkey": keys, "o_totalprice": means, "o_orderdate": [datetime.datetime(2024, 3, 1)] * len(keys)}, "a")
    got, want = _profiles(spark, tmp_path)
    assert repr(sorted(got.items())) == repr(sorted(want.items())) and len(got) == len(means)
    assert sum(abs(got[k][14] - means[k]) > 0 for k in range(2000)) == 2000


def test_customers_of_empty_tables(spark, tmp_path):
    d = _copy(spark, tmp_path, **{t: vectors.table(spark, "/root/testdata/sf0.001", t).limit(0) for t in ("orders", "lineitem")})
    assert vectors.customer_profile(spark, d).count() == 0
    d = _copy(spark, tmp_path / "lines", orders=vectors.table(spark, "/root/testdata/sf0.001", "orders"), lineitem=vectors.table(spark, "/root/testdata/sf0.001", "lineitem").limit(0))
    assert vectors.customer_profile(spark, d).filter("embedding[15] = 0").count() == 150


def test_all_sets_are_measured_on_all_rows(spark, tmp_path, monkeypatch):
    """Each collection that there is comes up, and ids with gaps or repeats lose or double no row of the longer vectors."""
    d = "/root/testdata/sf0.001"
    seen = {}
    monkeypatch.setattr(workloads, "_measure", lambda w, df, config, variants, params, runs=3: seen.update({params["set"]: (df.count(), config.dim)}) or [])
    monkeypatch.setattr(workloads, "ENOUGH", 0)
    workloads.w3_all_sets(spark, d)
    names = vectors.collection.__doc__.partition(": ")[2].rstrip(".").split(", ")
    assert set(seen) == set(names) and seen["conv_hash"] == (vectors.table(spark, d, "conversations").select("conv_id").distinct().count(), 128)

    e = vectors.table(spark, d, "embeddings")
    told = lambda df: sorted((r.vec_id, *r.embedding) for r in df.collect())
    plain = {dim: told(vectors.ladder(spark, d, dim)) for dim in (64, 128, 192)}
    assert plain == {dim: told(vectors.collection("emb_ladder", spark, d, dim=dim)) for dim in (64, 128, 192)}
    apart = _copy(spark, tmp_path / "gaps", embeddings=e.withColumn("vec_id", F.col("vec_id") * 1_000_003 - 9))
    assert [(v[0] * 1_000_003 - 9, *v[1:]) for v in plain[192]] == told(vectors.collection("emb_ladder", spark, apart, dim=192))
    twice = _copy(spark, tmp_path / "twice", embeddings=e.withColumn("vec_id", F.col("vec_id") % 3))
    assert vectors.collection("emb_ladder", spark, twice, dim=192).filter("size(embedding) = 192").count() == e.count()
    none = _copy(spark, tmp_path / "none", embeddings=e.limit(0))
    assert vectors.collection("emb_ladder", spark, none, dim=128).count() == 0


def test_common_shingles_decide_on_no_link(spark, monkeypatch):
    """Whichever shingles are taken to be common, the links are those of comparing all pairs."""
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text").persist()
    rows = docs.collect()
    sets, forest = [x for x in shingles.shingle_sets(pa.array([r.text for r in rows]), 4)], jaccard_join.Forest()
    for a in range(len(rows)):
        for b in range(a):
            both = len(np.intersect1d(sets[a], sets[b], assume_unique=True))
            if both and 100 * both >= 85 * (len(sets[a]) + len(sets[b]) - both):
                forest.union(rows[a].doc_id, rows[b].doc_id)
    want = {(r.doc_id, len(x), forest.find(r.doc_id)) for r, x in zip(rows, sets, strict=True)}
    every = np.unique(np.concatenate(sets))
    assert len({w[2] for w in want}) < len(want)
    for some in (every[:0], every[::2], every):
        monkeypatch.setattr(jaccard_join, "common_shingles", lambda *_, some=some: some)
        assert {tuple(r) for r in jaccard_join.jaccard_components(docs, 4, 85, 100).collect()} == want


def test_kernels_hold_a_block_and_agree():
    """Tables of scores are of a bounded block of rows, and all forms find the nearest centroid, the first of equal ones."""
    rng = np.random.default_rng(4)
    for dim, width, k in ((64, 16, 256), (64, 4, 13), (60, 8, 7), (64, 32, 300), (20, 20, 5)):
        x = np.round(rng.normal(size=(3000, dim)) * 4)
        config = catalog.PQConfig(dim=dim, width=width, k=k, split="pad")
        one = PQModel(config, [np.zeros((1, width))] * config.chunks)
        model = PQModel(config, [np.concatenate([p[: k - 2], p[:2]]) for p in (kernels.piece(x, one, j) for j in range(config.chunks))])
        want = np.stack([((kernels.piece(x, model, j)[:, None] - b) ** 2).sum(axis=2).argmin(axis=1) for j, b in enumerate(model.books)], axis=1)
        for strategy in ("lane_by_dimension", "matrix", "expanded", "staged"):
            assert (kernels.encode(x, model, strategy) == want).all()
    config = catalog.config(width=4, k=256)
    model = PQModel(config, [rng.normal(size=(256, 4)) for _ in range(16)])
    tracemalloc.start()
    kernels.encode(rng.normal(size=(6000, 64)), model, "matrix")
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 60e6  # 16 whole tables of 6000 rows are 197 MB


def test_a_collection_is_made_once(spark, tmp_path, monkeypatch):
    told = str(tmp_path / "made")

    def tell(batches):
        for batch in batches:
            with open(told, "a") as out:
                out.write("x" * batch.num_rows)
            yield batch

    e = vectors.table(spark, "/root/testdata/sf0.001", "embeddings").select("vec_id", "embedding").coalesce(1)
    monkeypatch.setattr(vectors, "collection", lambda *a, **b: e.mapInArrow(tell, e.schema))
    for least in (400, 1200):
        df, dim = workloads._rows(spark, "", "any", least)
        assert df.count() == {400: 500, 1200: 1500}[least] and dim == 64 and df.select("vec_id").distinct().count() == df.count()
        assert len(open(told).read()) == 500
        os.remove(told)
        df.unpersist()


def test_hashed_vectors_follow_the_counts(spark):
    """The vectors are the SQL's counts over their norm; ids that repeat share their sum, and null ids have none."""
    texts = [(1, "Hello World hello"), (2, None), (3, ""), (4, "\u00c4\u212a \u0130x 123 a\nb"), (4, "again hello"), (None, "x y"), (None, "x"), (5, "a " * 500 + "b")]
    t = spark.createDataFrame(texts, "doc_id long, text string").repartition(3)
    for dim in (256, 3):
        counts = {}
        for r in vectors.hashed(t.filter("doc_id is not null"), "doc_id", dim).collect():
            counts.setdefault(r.doc_id, np.zeros(dim, np.int64))[r.bucket] = r.n
        want = [(i, tuple((n / (np.sqrt(float((n * n).sum())) or 1.0)).astype(np.float32).tolist())) for i, n in ((i, counts.get(i, np.zeros(dim, np.int64))) for i, _ in texts)]
        got = [(r.vec_id, tuple(r.embedding)) for r in vectors.hashed_vectors(t, "doc_id", dim).collect()]
        assert sorted(got, key=repr) == sorted(want, key=repr)


def test_units_take_the_largest_finite_component(spark):
    rows = [([1.0, None],), (None,), ([float("inf"), -3000.0, float("nan")],), ([],)]
    df = spark.createDataFrame(rows, "embedding array<float>")
    assert train.units(df, catalog.config(), "embedding") == train.units(spark.createDataFrame([([3000.0],)] * 4, "embedding array<double>"), catalog.config(), "embedding")
    assert train.units(df.limit(0), catalog.config(), "embedding")[0] == train.UNIT


def test_scans_pass_on_only_what_may_be_near(spark):
    """Exact and asymmetric neighbours are those of whole tables of distances, ties by number; far rows are neither laid side by side nor sorted."""
    rng = np.random.default_rng(8)
    x = np.round(rng.normal(size=(900, 64)))  # whole numbers: many equal distances
    x[100:140] = x[7]
    df = spark.createDataFrame([(k, v) for k, v in enumerate(x.tolist())], "vec_id long, embedding array<double>").persist()
    q = df.filter("vec_id % 20 = 0")
    asked = range(0, 900, 20)
    far = ((x[:, None] - x[None]) ** 2).sum(axis=2)
    nearest = lambda d, k: {(i, r + 1, v, d[i, v]) for i in asked for r, v in enumerate(sorted((v for v in range(900) if v != i), key=lambda v: (d[i, v], v))[:k])}
    for k in (1, 10, 2000):
        assert {tuple(r) for r in search.exact(q, df, k).collect()} == nearest(far, k)
    model = train.lloyd(df, catalog.config(width=8, iterations=1))
    luts = search.tables(x, model)
    code = kernels.encode(x, model)
    about = np.zeros((900, 900))
    for j in range(model.chunks):
        about += luts[:, j][:, code[:, j]]
    codes = encode.encode(df, model).persist()
    for k in (1, 10, 2000):
        assert {tuple(r) for r in search.adc(q, codes, model, k).collect()} == nearest(about, k)
    places = {(i, v): r for i, r, v, _ in nearest(about, 900)}
    wanted = spark.createDataFrame([(i, v) for i in asked for v in (3, 7, 121, 888)], "query_id long, vec_id long")
    assert {tuple(r) for r in search.adc_ranks(q, codes, model, wanted).collect()} == {(i, v, places[i, v]) for i in asked for v in (3, 7, 121, 888)}

    best, passed = search._Top(np.arange(900), 10, True), 0
    for a in range(0, 900, 30):
        row, at, dist = search._within(about[a : a + 30], best.bound)
        best.add(at, row + a, dist)
        best._settle()
        passed += len(at)
    assert passed < 900 * 900 / 8 and best.rows().num_rows == 9000
