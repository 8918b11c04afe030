"""Training through ciphers, against native training and hand counts."""

import math
import pickle

import pytest
from pyspark.sql import functions as F

from vboost.functions import codec, metrics
from vboost.functions.codec import Budget
from vboost.he.base import Mock
from vboost.he.paillier import FixedBase, keygen
from vboost.operators import align, histogram, sampling, surface
from vboost.plans import baselines, exchange, protocol
from vboost.plans.grow import train
from vboost.plans.params import FederatedSpec, Ledger, Params, Party, guard, schedule
from vboost.sources.io import bucketed

SPEC = FederatedSpec((Party("a", "active", ("x0", "x1")), Party("p", "passive", ("x2", "x3"))))
SPEC3 = FederatedSpec((Party("a", "active", ("x0",)), Party("p", "passive", ("x1", "x2")), Party("q", "passive", ("x3",))))


@pytest.fixture(scope="module")
def data(spark):
    rows = [(i, 1 if (i % 7) + 2 * (i % 5) > 6 else 0, float(i % 7), float(i % 3), float(i % 5), float(i % 11)) for i in range(300)]
    return spark.createDataFrame(rows, "inst_id long, y int, x0 double, x1 double, x2 double, x3 double").cache()


def shape(model):
    return {(r["tree"], r["node"], r["fid"], r["bin"], r["count"], str(r["weight"])) for r in model.node_rows()}


@pytest.mark.parametrize("changes", [{}, {"sparse": True}, {"colsample": 0.5, "subsample": 0.7}, {"rounding": "round", "tight_h": True}])
def test_ciphers_grow_the_native_trees(data, changes):
    p = Params(trees=2, max_depth=2, **changes)
    assert shape(train(data, SPEC, p)) == shape(train(data, SPEC, p.but(he="mock")))


def test_real_ciphers_grow_the_native_trees(data):
    p = Params(trees=2, max_depth=2, precision_bits=40, key_bits=512)
    key = keygen(512, seed=9)
    assert shape(train(data, SPEC, p)) == shape(train(data, SPEC, p.but(he="paillier"), key=key))


@pytest.mark.parametrize("output,bits", [("multi", 1024), ("multi", 220), ("single", 1024)])
def test_three_classes_on_ciphers(data, output, bits):
    """Vectors in one cipher (and several infos to a package), in two ciphers, and a tree for each class."""
    rows = data.withColumn("y", (F.col("inst_id") % 3).cast("int"))
    p = Params(trees=1, classes=3, output=output, max_depth=2, goss=None, key_bits=bits, precision_bits=40)
    b = p.budget(300)
    assert (b.n_k(3), b.members(3) > 1) == ((1, True) if bits == 1024 else (2, False))
    assert shape(train(rows, SPEC, p)) == shape(train(rows, SPEC, p.but(he="mock")))


def test_three_parties_take_their_turns(data):
    order = ("q", "a", "p")
    m = train(data, SPEC3, baselines.mix(Params(trees=3, max_depth=2, goss=None, he="mock", party_order=order)))
    assert [{r["party"] for r in m.node_rows() if r["tree"] == t and r["party"]} for t in range(3)] == [{x} for x in order]
    told = {(r["tree"], r["receiver"]) for r in m.ledger.rows if r["kind"] == "enc_gh"}
    assert told == {(0, "q"), (2, "p")}  # the active party's own tree needs no cipher
    assert {(r["sender"], r["receiver"]) for r in m.ledger.rows if r["kind"] == "assign"} == {(s, t) for s in order for t in order if s != t}
    plan = schedule(SPEC3, Params(mode="layered", all_passives=True))
    assert plan.eligible(0, 0) == ("p", "q") and plan.eligible(0, 4) == ("a",)
    with pytest.raises(ValueError):
        schedule(SPEC3, Params(mode="mix", party_order=("a",)))


def test_federated_prediction(data, spark):
    for spec, classes in ((SPEC, 1), (SPEC3, 1), (SPEC3, 3)):
        rows = data.withColumn("y", (F.col("inst_id") % 3).cast("int")) if classes > 1 else data
        m = train(rows, spec, Params(trees=3, max_depth=3, classes=classes, output="multi" if classes > 1 else "single"))
        frames = {p.name: rows.select("inst_id", *p.columns, *(["y"] if p.role == "active" else [])) for p in spec.parties}
        ledger = Ledger()
        told = {r["inst_id"]: (r["y"], r["score"]) for r in m.predict_federated(frames, ("y",), ledger).collect()}
        assert told == {r["inst_id"]: (r["y"], r["score"]) for r in m.predict(rows, ["inst_id", "y"]).collect()}
        assert ledger.items("directions") == 300 * (len(spec.parties) - 1)
    fewer = m.predict_federated(frames | {"p": frames["p"].where("inst_id < 10")})
    assert fewer.count() == 10


def test_unknown_ciphers_and_short_keys_raise(data):
    with pytest.raises(ValueError):
        train(data, SPEC, Params(trees=1, he="nonsense"))
    with pytest.raises(ValueError):
        train(data, SPEC, Params(trees=1, he="mock", key_bits=64))


def test_large_gradients(spark):
    """Squared loss with labels far beyond 1,024; a gradient beyond the range raises."""
    df = spark.createDataFrame([(float(x),) for x in (2000.0, 5000.0, -5000.25, 1e8, -1e8 + 0.5, 0.0)], "g double").withColumn("h", F.lit(1.0))
    r = histogram.fixed_columns(df, 53).select((codec.unlimb(F.col("g0_hi"), F.col("g0_lo")).cast("string")).alias("v"), "g").collect()
    assert all(int(x["v"]) == int(x["g"] * 2**53) for x in r)
    for bad in (1e12, float("nan"), float("inf")):
        with pytest.raises(Exception, match="fixed-point range"):
            histogram.fixed_columns(spark.createDataFrame([(bad, 1.0)], "g double, h double"), 53).collect()
    rows = spark.createDataFrame([(i, 10_000.0 * (i % 4), float(i % 4), float(i % 3)) for i in range(120)], "inst_id long, y double, x0 double, x1 double")
    spec = FederatedSpec((Party("a", "active", ("x1",)), Party("p", "passive", ("x0",))))
    p = Params(trees=8, max_depth=2, objective="squared", goss=None, learning_rate=0.7, grad_bound=40_000.0)
    m = train(rows, spec, p)
    worst = m.predict(rows, ["y"]).agg(F.max(F.abs(F.col("score") - F.col("y")))).first()[0]
    assert worst < 1000
    assert shape(train(rows, spec, p.but(trees=1))) == shape(train(rows, spec, p.but(trees=1, he="mock")))
    with pytest.raises(Exception, match="beyond the declared bounds"):
        train(rows, spec, p.but(trees=1, he="mock", grad_bound=100.0))


def test_sampling_keeps_its_share_where_gradients_tie(spark):
    rows = spark.range(20_000).select(F.col("id").alias("inst_id"), F.when(F.col("id") % 2 == 0, 0.5).otherwise(-0.5).alias("g"), F.lit(0.25).alias("h"))
    kept = sampling.goss(rows, 0.2, 0.1)
    n, total = kept.count(), kept.agg(F.sum("h")).first()[0]
    assert abs(n - 6000) < 300 and abs(total / 0.25 - 20_000) < 1500
    some = rows.withColumn("g", F.when(F.col("inst_id") < 1000, 3.0).otherwise(F.col("g")))
    kept = sampling.goss(some, 0.2, 0.1)
    assert kept.where("inst_id < 1000 AND amp = 1").count() == 1000 and abs(kept.count() - 6000) < 300
    assert len(sampling.some_features(10, 0.35, 1)) == 4 and sampling.some_features(10, 1.0, 1) == list(range(10))


def test_ciphers_leave_the_pool_behind_and_invert_at_once():
    key = keygen(256, seed=3)
    key.pool(3)
    assert pickle.loads(pickle.dumps(key)).ready == [] and len(key.ready) == 3
    a, b = [key.encrypt(x) for x in (50, 60, 70)], [key.encrypt(x) for x in (1, 2, 3)]
    assert [key.decrypt(x) for x in key.public().sub_all(a, b)] == [49, 58, 67] and key.public().sub_all([], []) == []


def test_encryption_is_dealt_over_all_tasks(spark):
    rows = spark.range(400).coalesce(1).select(F.col("id").alias("inst_id"), F.lit(0.5).alias("g"), F.lit(0.25).alias("h"))
    found = protocol.encrypt_rows(rows, Mock(), Budget(400))
    assert found.count() == 400 and found.select(F.spark_partition_id()).distinct().count() == int(spark.conf.get("spark.sql.shuffle.partitions"))


def test_obfuscators_by_tables():
    """Powers by tables equal the built-in's; obfuscators are n-th residues, all different; tables stay where they were filled."""
    t = FixedBase(12_345, 1_000_003, 70)
    assert all(t.power(e) == pow(12_345, e, 1_000_003) for e in (0, 1, 255, 256, 2**64 + 12_345, 2**70 - 1))
    key = keygen(256, seed=3)
    found = [key._obfuscator() for _ in range(20)]
    order = math.lcm(key.p - 1, key.q - 1)
    assert len(set(found)) == 20 and all(pow(x, order, key.n2) == 1 for x in found)
    assert key.tables is not None and pickle.loads(pickle.dumps(key)).tables is None
    assert key.decrypt(key.encrypt(77)) == 77 and key.decrypt_plain(key.encrypt(78)) == 78


def test_compressed_vectors_and_bounds():
    b = Budget(1000, 20)
    k = b.members(3)
    values = [codec.compress([codec.pack(0.5, 0.1, b), codec.pack(-0.25, 0.2, b), codec.pack(0.0, 0.0, b)], b) for _ in range(k)]
    assert codec.decompress(codec.compress(values, b, 3), k, b, 3) == values
    assert codec.apart(0.5, 0.25, b) == [int(1.5 * 2**20), 2**18]
    with pytest.raises(OverflowError):
        codec.pack(1.5, 0.0, b)


def test_guard_of_every_message():
    guard("active", "directions", ["inst_id", "bits"])
    guard("passive", "split_choice", ["split_uid", "node"])
    for role, kind, columns in (("passive", "assign", ["inst_id", "node", "y"]), ("active", "split_info", ["split_uid", "bin"]), ("passive", "enc_gh", ["inst_id", "c", "g"]), ("active", "chosen", ["fid"])):
        with pytest.raises(PermissionError):
            guard(role, kind, columns)


def test_homomorphic_restore_and_subtraction(spark):
    """Sparse cells equal dense ones, and a sibling by subtraction equals the one built."""
    rows = spark.createDataFrame([(i, 1 + i % 2, [i % 3, i % 5], (i % 7) / 7, 0.25) for i in range(200)], "inst_id long, node int, bins array<int>, g double, h double")
    mock, budget = Mock(), Budget(200)
    enc = protocol.encrypt_rows(rows, mock, budget).join(rows.select("inst_id", "node", "bins"), "inst_id")
    seen = lambda cells: {(r["node"], r["fid"], r["bin"], r["cnt"], bytes(r["c"][0])) for r in cells.collect()}
    dense = protocol.cipher_histogram(enc, mock)
    assert seen(protocol.cipher_histogram(enc, mock, [0, 2])) == seen(dense)
    parent = protocol.cipher_histogram(enc.withColumn("node", F.lit(0)), mock)
    other = protocol.cipher_subtract(parent, dense.where("node = 1"), {1: 2}, mock)
    assert seen(other) == seen(dense.where("node = 2"))
    assert other.agg(F.sum("inversions")).first()[0] == dense.where("node = 2").count()


def test_bucketed_joins_move_nothing(spark):
    a, b = (bucketed(spark.range(1000).select(F.col("id").alias("inst_id"), F.lit(k).alias(f"v{k}")), "inst_id") for k in range(2))
    assert "Exchange" not in surface.plan_of(a.hint("merge").join(b, "inst_id"))


def test_no_ciphers_or_places_are_broadcast(data, spark, monkeypatch):
    """Joins by instance are merges even where the files are small enough to broadcast."""
    plans = []

    def seen(original):
        return lambda frame, *a, **k: plans.append(surface.plan_of(frame)) or original(frame, *a, **k)

    monkeypatch.setattr(protocol, "cipher_histogram", seen(protocol.cipher_histogram))
    monkeypatch.setattr(histogram, "limb_cells", seen(histogram.limb_cells))
    monkeypatch.setattr(exchange, "bucketed", seen(exchange.bucketed))
    train(data, SPEC, baselines.base(Params(trees=1, max_depth=2, he="mock")))
    rows = data.select("inst_id", F.lit(0).alias("node"), F.array(F.col("x0").cast("int")).alias("bins"), F.lit(0.5).alias("g"), F.lit(0.25).alias("h"))
    protocol.passive_sums(rows, Mock(), Budget(300), "s").collect()
    joined = [p for p in plans if "Join" in p]
    assert len(joined) >= 5 and all("Broadcast" not in p for p in joined)


def test_hints_choose_the_join(spark):
    assert "ShuffledHashJoin" in surface.plan_of(surface.join_shuffle_hash(spark, "/root/testdata/sf0.001"))
    assert "SortMergeJoin" in surface.plan_of(surface.join_merge_hint(spark, "/root/testdata/sf0.001"))


def test_intersections_with_fresh_secrets(spark):
    one, two = spark.range(0, 40).toDF("inst_id"), spark.range(25, 70).toDF("inst_id")
    for found in (align.intersect_dh(one, two), align.intersect_digest(one, two)):
        assert sorted(r[0] for r in found.collect()) == list(range(25, 40))
    assert align.draw_exponent() != align.draw_exponent()


def test_brute_split_and_band(data, spark):
    m = train(data, SPEC, Params(trees=1, max_depth=1, goss=None))
    root = next(r for r in m.node_rows() if r["node"] == 0)
    from vboost.operators import binning

    rows = binning.apply(data, SPEC.columns, m.edges, ["y"]).withColumn("g", 0.5 - F.col("y")).withColumn("h", F.lit(0.25))
    best = baselines.brute_split(rows, 4, 1.0, 32).first()
    assert (best["fid"], best["bin"]) == (root["fid"], root["bin"])
    ours = metrics.auc(train(data, SPEC, Params(trees=5, goss=None)).predict(data, ["inst_id", "y"])).first()[0]
    assert abs(metrics.auc(baselines.mllib(data, SPEC, 5)).first()[0] - ours) < 0.05


def test_patience_and_target(data):
    still = data.withColumn("y", (F.col("inst_id") * 7919 % 2).cast("int"))
    m = train(still, SPEC, Params(trees=12, max_depth=1, goss=None, patience=2), evaluate=True, test=data)
    assert len(m.history) < 12
    m = train(data, SPEC, Params(trees=12, max_depth=3, goss=None), evaluate=True, target=0.97)
    assert m.history[-1]["quality"] >= 0.97 and metrics.trees_to_target(m.history, "quality", 0.97) == len(m.trees)


def test_backend_by_name():
    assert isinstance(exchange.backend(Params(he="mock")), Mock)
