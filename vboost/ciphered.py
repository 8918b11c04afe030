"""Queries that run the exchange on ciphers, with the SQL of the same sums and trees in plain."""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .fixture import BASE_SQL, PLAIN, R, SPEC, base_rows, fixed_rows, tree_frame, tree_sql
from .functions import codec, costs
from .functions.codec import Budget
from .he.base import Backend, Mock
from .he.paillier import keygen
from .operators import histogram
from .plans import baselines, protocol
from .plans.exchange import Federation
from .plans.grow import grow_tree, train
from .plans.params import FederatedSpec, Ledger, Params, Party, schedule
from .sources import workloads
from .sources.io import row_counts

#: Reproducible keys and secrets of these fixtures; a run draws its own.
SECRET = "fixture"


def cipher_sums(spark: SparkSession, sf_dir: str, key: Backend, packing: bool = True, compress: bool = True, sparse: bool = False) -> DataFrame:
    """Prefix sums of the passive party through pack, fold, mask, compress, open and unpack, over all orders."""
    base = base_rows(spark, sf_dir)
    budget = Budget(max(base.count(), 1), 30 if key.iota < 400 else R, iota=key.iota)
    rows = base.select("inst_id", "node", F.slice("bins", 2, 2).alias("bins"), "g", "h")
    out = protocol.passive_sums(rows, key, budget, SECRET, packing, compress, default_bins=[3, 15] if sparse else None)
    real = lambda c: (F.get(c, F.lit(0)).cast("decimal(38,0)").cast("double") / float(2**budget.r)).alias(c)
    return out.select((F.col("fid") + 1).alias("fid"), "bin", F.col("sample_count").cast("bigint").alias("cnt"), real("g"), real("h"))


SUMS_SQL = f"WITH {BASE_SQL} SELECT fid, bin, CAST(cnt_l AS BIGINT) AS cnt, gl AS g, hl AS h FROM s WHERE fid > 0 AND cnt_t > cnt_l"


def federation(spark: SparkSession, sf_dir: str, params: Params, ledger: Ledger | None = None) -> tuple[Federation, DataFrame]:
    rows = base_rows(spark, sf_dir)
    budget = params.budget(max(rows.count(), 1))
    key = keygen(params.key_bits, seed=7) if params.he == "paillier" else None
    return Federation(rows, SPEC, params, budget, ledger if ledger is not None else Ledger(), [0, 3, 15], key, SECRET), rows


#: A 256-bit key holds one packed integer of these sums.
SMALL = {"he": "paillier", "key_bits": 256, "precision_bits": 40}


def tree_on_ciphers(spark, sf_dir, tree: int = 0, **changes) -> DataFrame:
    """The first tree of the fixture, grown through the exchange."""
    params = PLAIN.but(**changes)
    fed, rows = federation(spark, sf_dir, params)
    grown, _ = fed.grow(rows.select("inst_id", "g", "h"), schedule(SPEC, params), tree)
    fed.close()
    return tree_frame(spark, grown, params.reg_lambda)


def tree1_mo(spark, sf_dir, he: str = "native") -> DataFrame:
    """A vector tree of the classes 1 - y and y at p = 1/2."""
    params = PLAIN.but(he=he, classes=2, output="multi")
    rows = base_rows(spark, sf_dir).withColumn("g", F.array("g", -F.col("g"))).withColumn("h", F.array("h", "h"))
    if he == "native":
        grown = grow_tree(histogram.fixed_columns(rows, R, 2).drop("node", "g", "h"), SPEC, params, schedule(SPEC, params), 0, 0, 2)
    else:
        fed, _ = federation(spark, sf_dir, params)
        grown, _ = fed.grow(rows.select("inst_id", "g", "h"), schedule(SPEC, params), 0, 0, 2)
        fed.close()
    data = [(i, n.fid, n.bin, n.count, *[round(w, 9) for w in grown.weight(i, params.reg_lambda)]) for i, n in sorted(grown.nodes.items())]
    return spark.createDataFrame(data, "node int, fid int, bin int, cnt long, w0 double, w1 double")


def pack_mo_roundtrip(spark, sf_dir) -> DataFrame:
    """Sums of the first tree's vector gradients of 25 brands by part size, through several ciphers a row."""
    rows = workloads.ALL["w10"].load(spark, sf_dir)
    each = lambda f: F.transform(F.sequence(F.lit(0), F.lit(24)), f)
    rows = rows.select("inst_id", F.lit(0).alias("node"), F.array(F.col("p_size").cast("int")).alias("bins"), each(lambda j: 0.04 - (j == F.col("y")).cast("double")).alias("g"), each(lambda j: F.lit(0.0384)).alias("h"))
    budget = Budget(max(rows.count(), 1))
    out = protocol.passive_sums(rows, Mock(), budget, SECRET, classes=25)
    flat = out.select("bin", F.posexplode(F.arrays_zip("g", "h")).alias("class", "x"))
    real = lambda c: (F.round(F.col(f"x.{c}").cast("decimal(38,0)").cast("double") / float(2**R), 6) + 0.0).alias(c)
    return flat.select("bin", "class", real("g"), real("h"))


PACK_MO_SQL = """
WITH p AS (SELECT CAST(p_size AS INT) AS bin, CAST(replace(p_brand, 'Brand#', '') AS INT) - 1 AS y FROM part),
c AS (SELECT bin, class, sum(CAST(0.04 AS DOUBLE) - CASE WHEN y = class THEN 1 ELSE 0 END) AS g, sum(CAST(0.0384 AS DOUBLE)) AS h FROM p CROSS JOIN (SELECT CAST(unnest(range(25)) AS INT) AS class) k GROUP BY 1, 2),
s AS (SELECT bin, class, sum(g) OVER (PARTITION BY class ORDER BY bin) AS g, sum(h) OVER (PARTITION BY class ORDER BY bin) AS h FROM c)
SELECT bin, class, round(g, 6) + 0 AS g, round(h, 6) + 0 AS h FROM s WHERE bin < (SELECT max(bin) FROM p)
"""


def fixed_point_sums(spark, sf_dir) -> DataFrame:
    """Exact sums of prices at 30 fractional bits by status, from limbs."""
    high, low = codec.limbs(F.col("o_totalprice").cast("double") / 500_000, 30)
    rows = spark.read.parquet(f"{sf_dir}/orders.parquet").select("o_orderstatus", high.alias("hi"), low.alias("lo"))
    total = rows.groupBy("o_orderstatus").agg(F.sum("hi").alias("hi"), F.sum("lo").alias("lo"))
    return total.select("o_orderstatus", codec.unlimb(F.col("hi"), F.col("lo")).cast("string").alias("total"))


def eta_nk_table(spark, sf_dir) -> DataFrame:
    """Classes a cipher holds and ciphers a row needs, for 1 to 25 classes and the rows of three tables."""
    out = []
    for n in row_counts(spark, sf_dir, orders="o_orderkey", lineitem="l_orderkey", events="event_id").values():
        b = Budget(n)
        out += [(n, k, b.b_gh, b.slots, b.n_k(k)) for k in range(1, 26)]
    return spark.createDataFrame(out, "n long, classes int, b_gh int, slots int, n_k int")


ETA_SQL = """
WITH t AS (SELECT count(o_orderkey) AS m FROM orders UNION ALL SELECT count(l_orderkey) FROM lineitem UNION ALL SELECT count(event_id) FROM events),
b AS (SELECT greatest(m, 1) AS n, length(bin(greatest(m, 1))) AS l FROM t), g AS (SELECT n, 107 + 2 * l AS b FROM b)
SELECT CAST(n AS BIGINT) AS n, CAST(k AS INT) AS classes, CAST(b AS INT) AS b_gh, CAST(1023 // b AS INT) AS slots, CAST(ceil(k / CAST(1023 // b AS DOUBLE)) AS INT) AS n_k FROM g CROSS JOIN (SELECT unnest(range(1, 26)) AS k) c
"""


def ledger_counts(spark, sf_dir) -> DataFrame:
    """What the ledger of one tree on ciphers counted: base and lean."""
    out = []
    for name, params in (("base", baselines.base(PLAIN)), ("lean", baselines.lean(PLAIN).but(goss=None))):
        ledger = Ledger()
        fed, rows = federation(spark, sf_dir, params.but(he="mock"), ledger)
        fed.grow(rows.select("inst_id", "g", "h"), schedule(SPEC, params), 0)
        fed.close()
        out.append((name, *[ledger.items(k) for k in ("enc", "rows_folded", "dec", "split_info", "shifts", "inversions", "assign")]))
    return spark.createDataFrame(out, "name string, enc long, folded long, dec long, infos long, shifts long, inversions long, assigned long")


#: The closed forms over the same tree's counts: cells, infos and smaller children by SQL.
LEDGER_SQL = tree_sql("0, 1, 2", "0, 1, 2").split("SELECT t.node")[0].rstrip() + """,
size AS (SELECT count(*) AS n, 1023 // (107 + 2 * length(bin(count(*)))) AS slots FROM b),
kids AS (SELECT node, count(*) AS n FROM n1 WHERE fid = 0 GROUP BY node),
small AS (SELECT node, n FROM kids ORDER BY n, node LIMIT 1),
root_infos AS (SELECT count(*) AS i FROM s WHERE fid > 0 AND cnt_t > cnt_l),
kid_infos AS (SELECT node, count(*) AS i FROM s1 WHERE fid > 0 AND cnt_t > cnt_l GROUP BY node),
total AS (SELECT (SELECT i FROM root_infos) + (SELECT sum(i) FROM kid_infos) AS i),
packs AS (SELECT ceil((SELECT i FROM root_infos) / CAST(slots AS DOUBLE)) + (SELECT sum(ceil(i / CAST(slots AS DOUBLE))) FROM kid_infos) AS p FROM size),
moved AS (SELECT size.n + coalesce((SELECT sum(kids.n) FROM kids JOIN q1 USING (node)), 0) AS m FROM size),
taken AS (SELECT count(*) AS c FROM c1 JOIN c AS up USING (fid, bin) JOIN small ON c1.node = small.node WHERE fid > 0 AND up.cnt > c1.cnt)
SELECT 'base' AS name, CAST(2 * n AS BIGINT) AS enc, CAST(2 * 2 * n * 2 AS BIGINT) AS folded, CAST(2 * total.i AS BIGINT) AS dec, CAST(2 * total.i AS BIGINT) AS infos, CAST(0 AS BIGINT) AS shifts, CAST(0 AS BIGINT) AS inversions, CAST(moved.m AS BIGINT) AS assigned FROM size, total, moved
UNION ALL SELECT 'lean', CAST(size.n AS BIGINT), CAST(2 * (size.n + small.n) AS BIGINT), CAST(p AS BIGINT), CAST(p AS BIGINT), CAST(total.i - p AS BIGINT), CAST(taken.c AS BIGINT), CAST(moved.m AS BIGINT) FROM size, small, total, packs, taken, moved
"""

SPEC3 = FederatedSpec((workloads.ALL["w1"].spec.parties[0], Party("bank", "passive", ("c_acctbal", "c_segment")), Party("census", "passive", ("c_nation", "c_region", "c_orders"))))


def predict_federated(spark, sf_dir) -> DataFrame:
    """Rows whose score by messages between two and three parties differs from the score by one party's features: none."""
    w = workloads.ALL["w1"]
    data = w.load(spark, sf_dir)
    out = []
    for spec in (w.spec, SPEC3):
        m = train(data, spec, Params(trees=4, max_depth=4))
        frames = {p.name: data.select("inst_id", *p.columns) for p in spec.parties}
        both = m.predict(data, ["inst_id"]).join(m.predict_federated(frames).withColumnRenamed("score", "told"), "inst_id")
        row = both.agg(F.count("*").alias("n"), F.count_if(F.col("score") != F.col("told")).alias("d")).first()
        out.append((len(spec.parties), row["n"], row["d"]))
    return spark.createDataFrame(out, "parties int, n long, differing long")


def three_parties(spark, sf_dir, mode: str) -> DataFrame:
    """Splits by owner of trees on ciphers with two passive parties, and how many nodes differ from the native trees'."""
    data = workloads.ALL["w1"].load(spark, sf_dir)
    p = Params(trees=3, max_depth=3, mode=mode, h_passive=2, h_active=1, all_passives=True, goss=None)
    models = [train(data, SPEC3, p.but(he=he)) for he in ("native", "mock")]
    nodes = [{(r["tree"], r["node"], r["fid"], r["bin"], r["count"]) for r in m.node_rows()} for m in models]
    owners = [r["party"] for r in models[1].node_rows() if r["party"]]
    return spark.createDataFrame([(mode, x.name, owners.count(x.name), len(nodes[0] ^ nodes[1])) for x in SPEC3.parties], "mode string, party string, splits long, differing long")


def encrypted_training(spark, sf_dir, variant: str, trees: int = 2, he: str = "mock") -> DataFrame:
    """A run on ciphers beside the native run: differing nodes, and the operations that the ledger counted."""
    data = workloads.ALL["w1"].load(spark, sf_dir)
    p = getattr(baselines, variant)(Params(trees=trees))
    native, ciphered = (train(data, workloads.ALL["w1"].spec, p.but(he=h)) for h in ("native", he))
    nodes = [{(r["tree"], r["node"], r["fid"], r["bin"], r["count"]) for r in m.node_rows()} for m in (native, ciphered)]
    ops = ciphered.ledger.operations()
    row = (variant, he, len(nodes[0] ^ nodes[1]), *[ops[k] for k in ("enc", "dec", "adds", "prefix", "shifts", "inversions")], costs.price(ops) / trees)
    return spark.createDataFrame([row], "variant string, he string, differing long, enc long, dec long, adds long, prefix long, shifts long, inversions long, cipher_seconds_a_tree double")


JOINT, LAYERED, ACTIVE, PASSIVE = tree_sql("0, 1, 2", "0, 1, 2"), tree_sql("1, 2", "0"), tree_sql("0", "0"), tree_sql("1, 2", "1, 2")
_LAYERS = {"mode": "layered", "h_passive": 1, "h_active": 1}
_KINDS = {"mock": {"he": "mock"}, "paillier": SMALL}
QUERIES = {
    "hist_mock_cipher": lambda s, d: cipher_sums(s, d, Mock()),
    "hist_mock_unpacked": lambda s, d: cipher_sums(s, d, Mock(), packing=False),
    "hist_mock_sparse": lambda s, d: cipher_sums(s, d, Mock(), sparse=True),
    "hist_paillier_small": lambda s, d: cipher_sums(s, d, keygen(256, seed=5), compress=False),
    "compress_roundtrip": lambda s, d: cipher_sums(s, d, keygen(512, seed=6)),
    "tree1_base_mock": partial(tree_on_ciphers, he="mock", packing=False, compress=False, subtract=False),
    "tree1_sparse_mock": partial(tree_on_ciphers, he="mock", sparse=True),
    **{f"tree1_joint_{k}": partial(tree_on_ciphers, **x) for k, x in _KINDS.items()},
    **{f"tree1_layered_{k}": partial(tree_on_ciphers, **x, **_LAYERS) for k, x in _KINDS.items()},
    **{f"tree1_mix_passive_{k}": partial(tree_on_ciphers, tree=1, mode="mix", **x) for k, x in _KINDS.items()},
    "tree1_mix_active_mock": partial(tree_on_ciphers, he="mock", mode="mix"),
    "tree1_mo": tree1_mo,
    "tree1_mo_mock": partial(tree1_mo, he="mock"),
    "pack_mo_roundtrip": pack_mo_roundtrip,
    "fixed_point_sums": fixed_point_sums,
    "eta_nk_table": eta_nk_table,
    "ledger_counts": ledger_counts,
    "predict_federated": predict_federated,
    "three_parties_joint": partial(three_parties, mode="joint"),
    "three_parties_mix": partial(three_parties, mode="mix"),
    "three_parties_layered": partial(three_parties, mode="layered"),
    **{f"encrypted_{v}": partial(encrypted_training, variant=v) for v in ("base", "lean", "mix", "layered")},
}


def _vector(sql: str) -> str:
    return f"SELECT node, fid, bin, cnt, w AS w0, -w AS w1 FROM ({sql}) z"


ORACLES = {
    **{k: SUMS_SQL for k in ("hist_mock_cipher", "hist_mock_unpacked", "hist_mock_sparse", "hist_paillier_small", "compress_roundtrip")},
    **{k: JOINT for k in ("tree1_base_mock", "tree1_sparse_mock", "tree1_joint_mock", "tree1_joint_paillier")},
    **{k: LAYERED for k in ("tree1_layered_mock", "tree1_layered_paillier")},
    **{k: PASSIVE for k in ("tree1_mix_passive_mock", "tree1_mix_passive_paillier")},
    "tree1_mix_active_mock": ACTIVE,
    "tree1_mo": _vector(JOINT),
    "tree1_mo_mock": _vector(JOINT),
    "pack_mo_roundtrip": PACK_MO_SQL,
    "fixed_point_sums": "SELECT o_orderstatus, CAST(sum(CAST(floor(CAST(o_totalprice AS DOUBLE) / 500000 * 1073741824) AS HUGEINT)) AS VARCHAR) AS total FROM orders GROUP BY 1",
    "eta_nk_table": ETA_SQL,
    "ledger_counts": LEDGER_SQL,
    "predict_federated": "SELECT CAST(k AS INT) AS parties, count(*) AS n, CAST(0 AS BIGINT) AS differing FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey CROSS JOIN (VALUES (2), (3)) t(k) GROUP BY k",
}
