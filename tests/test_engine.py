"""The quantizer: hand-made codes, equality of all strategies, and plans."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from pqspark import catalog
from pqspark.functions import kernels
from pqspark.model import PQConfig, PQModel
from pqspark.operators import encode, search, train
from pqspark.plans import cost
from pqspark.streaming import streams

SF = "/root/testdata/sf0.001"
MODEL = PQModel(PQConfig(dim=4, width=2, k=3), [np.array([[0.0, 0], [4, 0], [0, 4]]), np.array([[1.0, 1], [5, 5], [1, 1]])])


def test_codes_by_hand_with_ties():
    x = np.array([[3.0, 1, 1, 1], [0, 3, 6, 6], [2, 0, 3, 3]])
    want = [[1, 0], [2, 1], [0, 0]]  # equal centroids and equal distances: the smaller number
    for strategy in ("staged", "expanded", "matrix", "rowwise"):
        assert kernels.encode(x, MODEL, strategy).tolist() == want


@pytest.mark.parametrize("k,tile", [(16, 4), (13, 8), (1, 4), (17, 16)])
def test_all_kernels_agree(k, tile):
    rng = np.random.default_rng(k)
    x, books = rng.normal(size=(300, 12)), [rng.normal(size=(k, 4)) for _ in range(3)]
    model = PQModel(PQConfig(dim=12, width=4, k=k), books)
    want = kernels.encode(x, model, "rowwise")
    for score in kernels.SCORES:
        for order in kernels.ORDERS:
            for accumulate in ("gemm", "fma"):
                assert (kernels.encode(x, model, "tiled", score=score, order=order, tile=tile, accumulate=accumulate, block_rows=70) == want).all()


def test_centring_keeps_single_precision_right_far_from_the_origin():
    rng = np.random.default_rng(1)
    x, books = rng.normal(size=(500, 8)) + 1000, [rng.normal(size=(16, 8)) + 1000]
    model = PQModel(PQConfig(dim=8, width=8, k=16), books)
    assert (kernels.encode(x, model, precision="f32") == kernels.encode(x, model)).all()


@pytest.mark.parametrize("bits", [1, 4, 6, 8, 10, 12])
def test_packing_round_trip(bits):
    codes = np.random.default_rng(bits).integers(0, 1 << bits, (50, 5)).astype(np.int16)
    assert (kernels.unpack(kernels.pack(codes, bits), 5, bits) == codes).all()


def test_splits():
    with pytest.raises(ValueError):
        PQConfig(dim=10, width=4).chunks  # noqa: B018
    assert PQConfig(dim=10, width=4, split="pad").offsets() == [0, 4, 8, 12]
    assert PQConfig(dim=10, width=4, split="ragged").offsets() == [0, 5, 10]


def test_bad_rows(spark):
    rows = [(1, [0.0] * 4), (2, None), (3, [1.0]), (4, [1.0, None, 0.0, 0.0]), (5, [float("nan")] * 4)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    assert [r.vec_id for r in encode.encode(df, MODEL).collect()] == [1]
    assert {r.vec_id: r.codes for r in encode.encode(df, MODEL, on_bad="null_code").collect()}[3] is None
    assert encode.encode(df.limit(0), MODEL).count() == 0


def test_plan_has_no_shuffle_and_prunes_the_scan(spark, capsys):
    e = spark.read.parquet(f"{SF}/embeddings.parquet").filter("vec_id < 100")
    encode.encode(e, train.seeds(e, PQConfig(k=16, init="first"))).explain("formatted")
    plan = capsys.readouterr().out
    assert "Exchange" not in plan and "vec_id:bigint,embedding" in plan and "LessThan(vec_id,100)" in plan


def test_inertia_never_rises_and_partitions_do_not_matter(spark):
    e = spark.read.parquet(f"{SF}/embeddings.parquet")
    config = PQConfig(k=8, init="first", iterations=4)
    one, many = train.lloyd(e.coalesce(1), config), train.lloyd(e.repartition(7), config)
    assert one.diff(many) == 0 and one.inertia == sorted(one.inertia, reverse=True)


def test_asymmetric_distance_is_distance_to_the_decoded(spark):
    e = spark.read.parquet(f"{SF}/embeddings.parquet")
    model = train.seeds(e, PQConfig(k=16, init="first"))
    codes = encode.encode(e, model)
    q = e.filter("vec_id = 7")
    got = {r.vec_id: r.dist for r in search.adc(q, codes, model, 5).collect()}
    back = {r.vec_id: np.array(r.decoded) for r in encode.decode(codes, model).collect()}
    v = np.array(q.first().embedding, float)
    assert all(abs(((v - back[i]) ** 2).sum() - d) < 1e-9 for i, d in got.items())


def test_counts_of_the_cost_model():
    c = cost.counters(10, 64, 4, 256, "staged")
    assert c["arithmetic"] == 10 * 256 * 124 + 10 * 4 * 256 and c["score_cells"] == 0 and cost.working_set(16, 256) == 17_408


@pytest.mark.parametrize("name", ["encode_staged", "encode_definition", "lloyd_3", "adc_topk", "recall_at_10", "agg_cube", "stream_drift", "stream_counts", "stream_dedupe", "w11_insertion"])
def test_oracles(spark, name):
    con = duckdb.connect()
    for t in ("embeddings", "documents"):
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    df = catalog.queries()[name](spark, SF)
    rel = con.sql(catalog.oracle_sql()[name])
    cols = sorted(df.columns)
    at = [rel.columns.index(c) for c in cols]
    norm = lambda v: round(v, 6) if isinstance(v, float) else tuple(map(norm, v)) if isinstance(v, list) else v
    mine = sorted((tuple(norm(r[c]) for c in cols) for r in df.collect()), key=str)
    assert mine == sorted((tuple(norm(r[k]) for k in at) for r in rel.fetchall()), key=str)


def test_rows_past_the_watermark_are_dropped(spark, tmp_path):
    day = 86_400
    for batch in ([(10 * day, 1.0), (10 * day + 60, 3.0)], [(11 * day, 2.0)], [(day, 9.0), (10 * day, 9.0), (11 * day, 4.0)]):
        rows = spark.createDataFrame(batch, "s long, sse double").selectExpr("timestamp_seconds(s) AS ts", "sse")
        rows.coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    read = streams.read(spark, f"{tmp_path}/in", "ts timestamp, sse double")
    got = streams.settled(streams.drift(read), str(tmp_path), ["start"]).selectExpr("unix_seconds(start) AS s", "n", "mean_sse").collect()
    # Spark drops by the watermark of the batch before the last: day 1 is late, day 10 (open until day 11 less an hour) is not
    assert {r.s // day: (r.n, r.mean_sse) for r in got} == {10: (3, 13 / 3), 11: (2, 3.0)}


def test_checked_ranking_settles_near_ties():
    """Rows half-way between centroids, repeated centroids, and offsets that 32-bit floats can't carry: codes of the definition."""
    rng = np.random.default_rng(3)
    for offset, spread in ((0, 1), (1000, 1), (0, 1e-6), (1e5, 0.01), (0, 1e12), (0, 1e30)):
        book = rng.normal(size=(40, 4)) * spread + offset
        book[7], book[20] = book[3], book[3]
        x = np.concatenate([(book[rng.integers(0, 40, 400)] + book[rng.integers(0, 40, 400)]) / 2, book])
        model = PQModel(PQConfig(dim=4, width=4, k=40), [book])
        far = ((x[:, None, :] - book[None]) ** 2).sum(axis=2)
        code = kernels.encode(x, model)[:, 0]
        # half-way rows tie but for 64-bit rounding, which alone may choose between their two centroids
        assert (far[np.arange(len(x)), code] - far.min(axis=1) <= 1e-13 * (np.abs(x).max() + np.abs(book).max()) ** 2).all()
        assert (code[-40:] == np.where(np.isin(np.arange(40), [7, 20]), 3, np.arange(40))).all()


def test_more_centroids_than_a_smallint_holds(spark):
    model = PQModel(PQConfig(dim=1, width=1, k=40_000), [np.arange(40_000.0)[:, None]])
    df = spark.createDataFrame([(1, [39_999.0]), (2, [33_000.2])], "vec_id long, embedding array<double>")
    got = encode.encode(df, model, out="both")
    assert got.schema["codes"].dataType.simpleString() == "array<int>" and sorted(r.codes[0] for r in got.collect()) == [33_000, 39_999]
    codes = np.array([[40_000], [65_535]], np.int32)
    assert (kernels.unpack(kernels.pack(codes, 16), 1, 16) == codes).all()


@pytest.mark.parametrize("strategy", ["staged", "relational", "hof", "flat_expr", "scalar_udf", "lane_by_dimension"])
def test_bad_rows_are_treated_alike(spark, strategy):
    rows = [(1, [0.0] * 4), (2, None), (3, [1.0]), (4, [1.0, None, 0.0, 0.0]), (5, [float("nan")] * 4), (6, [4.0, 0.0, 5.0, 5.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    want = {1: [0, 0], 6: [1, 1]}
    assert {r.vec_id: r.codes for r in encode.encode(df, MODEL, strategy).collect()} == want
    assert {r.vec_id: r.codes for r in encode.encode(df, MODEL, strategy, on_bad="null_code").collect()} == want | dict.fromkeys((2, 3, 4, 5))
    with pytest.raises(Exception):  # noqa: B017
        encode.encode(df, MODEL, strategy, on_bad="fail").collect()


def test_training_on_large_values_does_not_overflow(spark):
    x = np.random.default_rng(1).normal(size=(6000, 4)) * 1e9
    df = spark.createDataFrame([(k, v.tolist()) for k, v in enumerate(x)], "vec_id long, embedding array<double>")
    model = train.lloyd(df, PQConfig(dim=4, width=4, k=4, iterations=4, init="first"))
    assert all(a >= b > 0 for a, b in zip(model.inertia, model.inertia[1:], strict=False))


def test_models_are_saved_and_loaded(spark, tmp_path):
    MODEL.save(spark, str(tmp_path / "m"))
    assert PQModel.load(spark, str(tmp_path / "m")).diff(MODEL) == 0


def test_adc_at_its_own_k_equals_all_pairs(spark):
    e = catalog.rows(spark, SF)
    model = catalog.first_k(spark, SF)
    codes = encode.encode(e, model)
    q = e.filter("vec_id % 20 = 0")
    few, all_ = search.adc(q, codes, model, 5), search.adc(q, codes, model, 10**6)
    want = {(r.query_id, r.rank): r.vec_id for r in all_.filter("rank <= 5").collect()}
    assert {(r.query_id, r.rank): r.vec_id for r in few.collect()} == want


def test_tables_are_checked_replaced_and_clustered(spark, tmp_path):
    from pqspark.sources import tables

    path = f"{tmp_path}/t"
    made = spark.range(100).select(F.col("id").alias("vec_id"), (F.col("id") % 3).cast("int").alias("list"))
    tables.write_lists(made, path)
    tables.write_lists(spark.read.parquet(path).filter("list > 0"), path)
    assert tables.scan_lists(spark, path, [0, 1]).count() == 33
    assert [p.name for p in tmp_path.iterdir()] == ["t"]
    with pytest.raises(ValueError, match="vec_id: bigint instead of int"):
        tables.read(spark, path, "vec_id int")
    with pytest.raises(ValueError, match="missing"):
        tables.read(spark, path, "embedding array<float>")
    codes = spark.range(200).select(F.col("id").alias("vec_id"), F.array((F.col("id") % 7).cast("smallint")).alias("codes"))
    parts = tables.sort_codes(codes).select(F.spark_partition_id().alias("p"), "codes", "vec_id").collect()
    by_part = {}
    for r in parts:
        by_part.setdefault(r.p, []).append((r.codes, r.vec_id))
    assert all(v == sorted(v) for v in by_part.values())
    ends = sorted((v[0], v[-1]) for v in by_part.values())
    assert all(a[1] < b[0] for a, b in zip(ends, ends[1:], strict=False))
