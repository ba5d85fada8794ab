"""The queries of the entry module: every measure, criterion, strategy, baseline, preparation and operator, with SQL where it exists."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import oracle
from .functions import encode, info, udf
from .functions.criteria import BUILT_IN, Criterion, Fold, criteria
from .operators import baselines, counts, greedy, metrics, models, relevance, sampling, sparse
from .operators.packed import SparseEngine
from .plans import layout
from .plans.dataset import Dataset, SparseDataset
from .plans.storage import folder, saved
from .sources import generator, tables, workloads
from .sources.tables import table
from .sources.workloads import GATE, STAR
from .streaming import events as streaming

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(fn):
        QUERIES[name or fn.__name__] = fn
        if sql:
            ORACLE_SQL[name or fn.__name__] = sql
        return fn

    return add


def r6(c: Column | str) -> Column:
    """Six decimals, and no negative zero."""
    return F.round(c, 6) + F.lit(0.0)


def scored(selection: greedy.Selection) -> DataFrame:
    return selection.to_df().select("step", "name", r6("score").alias("score"), r6("rel").alias("rel"))


def named_relevance(ds: Dataset | SparseDataset, strategy: str | None = None) -> DataFrame:
    return relevance.named(ds, relevance.relevance(ds, strategy)).select("name", r6("rel").alias("rel"))


# --- measures -------------------------------------------------------------------------------------------------------
_BASE = oracle.lines("gate")
_LONG = oracle.unpivoted(_BASE, GATE)


@query(f"WITH {_LONG}, {oracle.CELLS}, fx AS (SELECT feature, x, sum(c) AS c FROM cells GROUP BY ALL) SELECT {oracle._name('feature', GATE)} AS name, round(log2(sum(c)) - {oracle.g('c')} / sum(c), 6) + 0.0 AS entropy FROM fx GROUP BY feature")
def entropy_by_feature(spark, sf_dir):
    ds = workloads.lines(spark, sf_dir)
    return relevance.named(ds, info.entropy(counts.contingency(ds), ["feature"], ["x"])).select("name", r6("entropy").alias("entropy"))


@query(f"WITH {_LONG}, {oracle.CELLS}, fx AS (SELECT feature, x, sum(c) AS c FROM cells GROUP BY ALL), a AS (SELECT feature, {oracle.g('c')} AS s, sum(c) AS n FROM cells GROUP BY feature), b AS (SELECT feature, {oracle.g('c')} AS t FROM fx GROUP BY feature) SELECT {oracle._name('feature', GATE)} AS name, round((t - s) / n, 6) + 0.0 AS cond_entropy FROM a JOIN b USING (feature)")
def cond_entropy_by_feature(spark, sf_dir):
    """What the class leaves open once a feature is known."""
    ds = workloads.lines(spark, sf_dir)
    return relevance.named(ds, info.cond_entropy(counts.contingency(ds), "y", ["x"], ["feature"])).select("name", r6("cond_entropy").alias("cond_entropy"))


@query(f"WITH {_LONG}, {oracle.CELLS}, {oracle.relevance_of()}, {oracle.pairs()} SELECT {oracle._name('i', GATE)} AS name, round(p.mi, 6) + 0.0 AS mi, round(p.cmi, 6) + 0.0 AS cmi FROM pair p WHERE k = 2")
def redundancy_with_disc(spark, sf_dir):
    ds = workloads.lines(spark, sf_dir)
    return relevance.named(ds, relevance.redundancy(ds, "disc")).select("name", r6("mi").alias("mi"), r6("cmi").alias("cmi"))


@query(f"WITH {_LONG}, c3 AS (SELECT a.feature, a.x, b.x AS j, a.y, count(*) AS c FROM long a JOIN long b ON a.rid = b.rid AND b.feature = 2 GROUP BY ALL), xjy AS (SELECT feature, {oracle.g('c')} AS s, sum(c) AS n FROM c3 GROUP BY feature), xj AS (SELECT feature, {oracle.g('c')} AS t FROM (SELECT feature, x, j, sum(c) AS c FROM c3 GROUP BY ALL) GROUP BY feature), yy AS (SELECT feature, {oracle.g('c')} AS u FROM (SELECT feature, y, sum(c) AS c FROM c3 GROUP BY ALL) GROUP BY feature) SELECT {oracle._name('feature', GATE)} AS name, round(log2(n) + (s - t - u) / n, 6) + 0.0 AS pair_info FROM xjy JOIN xj USING (feature) JOIN yy USING (feature)")
def joint_pair_information(spark, sf_dir):
    ds = workloads.lines(spark, sf_dir)
    return relevance.named(ds, info.pair_info(counts.contingency(ds, "disc"))).select("name", r6("pair_info").alias("pair_info"))


@query(f"WITH c4 AS (SELECT qty, disc, tax, y, count(*) AS c FROM ({_BASE}) GROUP BY ALL), a AS (SELECT {oracle.g('c')} AS abc, sum(c) AS n FROM c4), b AS (SELECT {oracle.g('c')} AS cc FROM (SELECT disc, tax, sum(c) AS c FROM c4 GROUP BY ALL)), d AS (SELECT {oracle.g('c')} AS ac FROM (SELECT qty, disc, tax, sum(c) AS c FROM c4 GROUP BY ALL)), e AS (SELECT {oracle.g('c')} AS bc FROM (SELECT y, disc, tax, sum(c) AS c FROM c4 GROUP BY ALL)) SELECT round((abc + cc - ac - bc) / n, 6) + 0.0 AS cmi FROM a, b, d, e")
def cond_mi_set2(spark, sf_dir):
    """I(qty; y | disc, tax): the joint form that the linear criterion approximates."""
    return info.cond_mutual_info_set(workloads.lines(spark, sf_dir).columns(), "qty", "y", ["disc", "tax"]).select(r6("cmi").alias("cmi"))


@query(f"SELECT disc AS x, y, round(count(*) * 1.0 / (SELECT count(*) FROM lineitem), 6) AS p FROM ({_BASE}) GROUP BY ALL")
def proportions_disc(spark, sf_dir):
    cells = counts.contingency(workloads.lines(spark, sf_dir).only(["disc"]))
    return info.proportions(cells, ["x", "y"]).select("x", "y", r6("p").alias("p"))


for _n, _ds, _sql in (
    ("gate", lambda s, d: workloads.lines(s, d), oracle.relevance(oracle.lines("gate"), GATE)),
    ("xor", lambda s, d: workloads.lines(s, d, "xor"), oracle.relevance(oracle.lines("xor"), GATE)),
    ("rare", lambda s, d: workloads.lines(s, d, "rare"), oracle.relevance(oracle.lines("rare"), GATE)),
    ("noisy", lambda s, d: workloads.lines(s, d, "noisy"), oracle.relevance(oracle.lines("noisy"), GATE)),
    ("star", lambda s, d: workloads.star(s, d), oracle.relevance(oracle.star(), STAR)),
    ("embed", lambda s, d: workloads.embed(s, d), oracle.relevance(oracle.embed(), [f"e{i}" for i in range(64)])),
    ("embed_binary", lambda s, d: workloads.embed(s, d, binary=True), oracle.relevance(oracle.embed(binary=True), [f"e{i}" for i in range(64)])),
    ("events", lambda s, d: workloads.event_set(s, d), oracle.relevance(oracle.events(), oracle.event_features())),
    ("tokens_toxic", lambda s, d: workloads.token_set(s, d), oracle.relevance_sparse(oracle.token_rows("toxic"))),
    ("tokens_quality", lambda s, d: workloads.token_set(s, d, "quality"), oracle.relevance_sparse(oracle.token_rows("quality"))),
    ("tokens_lang", lambda s, d: workloads.token_set(s, d, "lang"), oracle.relevance_sparse(oracle.token_rows("lang"))),
    ("pages", lambda s, d: workloads.page_set(s, d), oracle.relevance_sparse(oracle.page_rows())),
    ("speakers", lambda s, d: workloads.speaker_set(s, d), oracle.relevance_sparse(oracle.speaker_rows())),
    ("bigrams_quality", lambda s, d: workloads.token_set(s, d, "quality", ngram=2), oracle.relevance_sparse(oracle.token_rows("quality", 2))),
    ("hashed_quality", lambda s, d: workloads.token_set(s, d, "quality", buckets=1 << 18), None),
):
    query(_sql, f"relevance_{_n}")(lambda s, d, f=_ds: named_relevance(f(s, d)))


@query(f"SELECT CAST(rank AS INT) AS step, name, rel FROM (SELECT row_number() OVER (ORDER BY round(rel, 12) DESC, feature) AS rank, {oracle._name('feature', GATE)} AS name, round(rel, 6) + 0.0 AS rel FROM (WITH {_LONG}, {oracle.CELLS}, {oracle.relevance_of()} SELECT * FROM rel))")
def ranking_by_relevance(spark, sf_dir):
    return relevance.rank(workloads.lines(spark, sf_dir)).select("step", "name", r6("rel").alias("rel"))


@query(f"SELECT name, CAST(card AS INT) AS card FROM (UNPIVOT (SELECT {', '.join(f'max({f}) + 1 AS {f}' for f in GATE)} FROM ({_BASE})) ON * INTO NAME name VALUE card)")
def cardinalities(spark, sf_dir):
    ds = workloads.lines(spark, sf_dir)
    return spark.createDataFrame([(f, ds.cards[f]) for f in ds.features], "name string, card int")


@query(f"WITH {_LONG}, {oracle.pairs()} SELECT {oracle._name('i', GATE)} AS a, {oracle._name('k', GATE)} AS b, round(mi, 6) + 0.0 AS mi, round(cmi, 6) + 0.0 AS cmi FROM pair WHERE i < k")
def pair_matrix(spark, sf_dir):
    ds = workloads.lines(spark, sf_dir)
    name = lambda c: F.element_at(F.array(*[F.lit(f) for f in ds.features]), F.col(c) + 1)
    return relevance.pair_matrix(ds).select(name("i").alias("a"), name("k").alias("b"), r6("mi").alias("mi"), r6("cmi").alias("cmi"))


# --- cells and strategies -------------------------------------------------------------------------------------------
_C2 = f"WITH {_LONG} SELECT CAST(feature AS INT) AS feature, x, y, count(*) AS c FROM long GROUP BY ALL"
_C3 = f"WITH {_LONG} SELECT CAST(a.feature AS INT) AS feature, a.x, b.x AS j, a.y, count(*) AS c FROM long a JOIN long b ON a.rid = b.rid AND b.feature = 2 GROUP BY ALL"


@query(_C2)
def cells_dense_2d(spark, sf_dir):
    return counts.contingency(workloads.lines(spark, sf_dir)).select("feature", "x", "y", "c")


for _s in ("explode", "arrow", "gsets", "blocks", "packed"):
    query(_C3, f"cells_{_s}")(lambda s, d, how=_s: counts.contingency(workloads.lines(s, d), "disc", how))


def _token(ds: SparseDataset, name: str) -> int:
    found = ds.vocabulary.where(F.col("name") == name).first()
    return found["feature"] if found else -1


_T3 = f"""WITH {oracle.token_rows('toxic')}, hit AS (SELECT rid FROM posts JOIN vocab USING (feature) WHERE name = 'idiot'),
    tot AS (SELECT y, count(*) AS t, count(*) FILTER (rid IN (SELECT rid FROM hit)) AS f FROM classes GROUP BY y),
    per AS (SELECT v.name, tot.y, t, f, coalesce(a, 0) AS a, coalesce(m, 0) AS m FROM vocab v CROSS JOIN tot
        LEFT JOIN (SELECT feature, y, count(*) AS a, count(*) FILTER (rid IN (SELECT rid FROM hit)) AS m FROM posts GROUP BY feature, y) z ON z.feature = v.feature AND z.y = tot.y)
    SELECT name, x, j, y, c FROM (SELECT name, y, unnest([{{'x': 1, 'j': 1, 'c': m}}, {{'x': 1, 'j': 0, 'c': a - m}}, {{'x': 0, 'j': 1, 'c': f - m}}, {{'x': 0, 'j': 0, 'c': t - a - f + m}}], recursive := true) FROM per) WHERE c > 0"""


@query(_T3)
def cells_sparse_3d(spark, sf_dir):
    """The cells of every token with one chosen token, counted by joining postings."""
    ds = workloads.token_set(spark, sf_dir)
    return relevance.named(ds, sparse.contingency(ds, _token(ds, "idiot"))).select("name", "x", "j", "y", "c")


@query(_T3)
def cells_sparse_packed(spark, sf_dir):
    """The same, what meets the chosen token being counted on packed rows."""
    ds = workloads.token_set(spark, sf_dir)
    j = _token(ds, "idiot")
    return relevance.named(ds, sparse.contingency(ds, j, met=saved(SparseEngine(ds).met(j), "met"))).select("name", "x", "j", "y", "c")


@query(f"""WITH {oracle.token_rows('toxic')} SELECT name FROM vocab WHERE feature NOT IN (SELECT q.feature FROM posts q WHERE q.rid IN (SELECT rid FROM posts JOIN vocab USING (feature) WHERE name = 'idiot'))""")
def features_never_met(spark, sf_dir):
    ds = workloads.token_set(spark, sf_dir)
    return sparse.never_met(ds, _token(ds, "idiot")).select("name")


@query(f"WITH {oracle.token_rows('toxic')} SELECT CAST(1 AS INT) AS j, y, count(*) AS c FROM posts JOIN vocab USING (feature) WHERE name = 'idiot' GROUP BY y")
def frequency_map(spark, sf_dir):
    ds = workloads.token_set(spark, sf_dir)
    return sparse.frequency_map(ds, _token(ds, "idiot"))


# --- greedy selection -----------------------------------------------------------------------------------------------
_WEIGHTS = {"mifs_half": ("mifs", 0.5, 1.0), "generic_beta_gamma": ("generic", 0.7, 0.3)}
for _c in ("mim", "mifs", "mifs_half", "jmi", "cmi", "mrmr", "cmim", "if", "icap", "generic_beta_gamma"):
    _kind, _beta, _gamma = _WEIGHTS.get(_c, (_c, 1.0, 1.0))
    for _t in ("gate", "xor"):
        query(oracle.greedy(oracle.lines(_t), GATE, _kind, 5, _beta, _gamma), f"greedy_{_c}_{_t}")(lambda s, d, c=_kind, b=_beta, g=_gamma, t=_t: scored(greedy.select(workloads.lines(s, d, t), 5, c, beta=b, gamma=g)))
for _c in ("mim", "mifs", "jmi", "cmi", "mrmr", "cmim", "icap"):
    query(oracle.greedy(oracle.star(), STAR, _c, 6), f"greedy_{_c}_star")(lambda s, d, c=_c: scored(greedy.select(workloads.star(s, d), 6, c)))
_E64 = [f"e{i}" for i in range(64)]
for _c in ("mim", "mrmr", "jmi", "cmim"):
    query(oracle.greedy(oracle.embed(), _E64, _c, 5), f"greedy_{_c}_embed")(lambda s, d, c=_c: scored(greedy.select(workloads.embed(s, d), 5, c)))
query(oracle.greedy(oracle.embed(binary=True), _E64, "mrmr", 5), "greedy_mrmr_embed_binary")(lambda s, d: scored(greedy.select(workloads.embed(s, d, binary=True), 5, "mrmr")))
for _c in ("mim", "mifs", "mrmr", "jmi", "cmi", "cmim", "icap"):
    query(oracle.greedy_sparse(oracle.token_rows("toxic"), _c, 6), f"greedy_{_c}_tokens")(lambda s, d, c=_c: scored(greedy.select(workloads.token_set(s, d), 6, c)))
for _n, _ds, _sql in (
    ("cmim_quality", lambda s, d: workloads.token_set(s, d, "quality"), oracle.token_rows("quality")),
    ("mrmr_lang", lambda s, d: workloads.token_set(s, d, "lang"), oracle.token_rows("lang")),
    ("mrmr_bigrams", lambda s, d: workloads.token_set(s, d, "quality", ngram=2), oracle.token_rows("quality", 2)),
    ("mrmr_pages", lambda s, d: workloads.page_set(s, d), oracle.page_rows()),
    ("jmi_speakers", lambda s, d: workloads.speaker_set(s, d), oracle.speaker_rows()),
):
    query(oracle.greedy_sparse(_sql, _n.split("_")[0], 6), f"greedy_{_n}")(lambda s, d, f=_ds, c=_n.split("_")[0]: scored(greedy.select(f(s, d), 6, c)))
for _b in (18, 20):
    # the hash isn't SQL; tests compare the hashed set with its dense form
    query(name=f"greedy_mrmr_hashed_{_b}")(lambda s, d, b=_b: scored(greedy.select(workloads.token_set(s, d, "quality", buckets=1 << b), 6, "mrmr")))

_MRMR = oracle.greedy(oracle.lines("gate"), GATE, "mrmr", 5)
for _n, _how in {"blocks": {"strategy": "blocks"}, "packed": {"strategy": "packed"}, "explode": {"strategy": "explode"}, "arrow": {"strategy": "arrow"}, "gsets": {"strategy": "gsets"}, "lazy": {"lazy": True}, "frame": {"state": "frame"}}.items():
    query(_MRMR, f"greedy_{_n}_mrmr")(lambda s, d, how=_how: scored(greedy.select(workloads.lines(s, d), 5, "mrmr", **how)))
for _c in ("cmim", "icap"):
    query(oracle.greedy(oracle.lines("gate"), GATE, _c, 5), f"greedy_lazy_{_c}")(lambda s, d, c=_c: scored(greedy.select(workloads.lines(s, d), 5, c, lazy=True)))
query(oracle.greedy(oracle.lines("gate"), GATE, "jmi", 5), "greedy_frame_jmi")(lambda s, d: scored(greedy.select(workloads.lines(s, d), 5, "jmi", state="frame")))


@query(_MRMR)
def greedy_resumed_mrmr(spark, sf_dir):
    """Three rounds that are logged, then five that continue from the log."""
    log = f"{folder(spark)}/log-{uuid.uuid4().hex}"
    greedy.select(workloads.lines(spark, sf_dir), 3, "mrmr", resume=log)
    return scored(greedy.select(workloads.lines(spark, sf_dir), 5, "mrmr", resume=log))


@query(_MRMR)
def greedy_sparsified_mrmr(spark, sf_dir):
    """Dense data counted as postings, the most frequent code of each feature left out."""
    return scored(greedy.select(layout.sparsified(workloads.lines(spark, sf_dir))[0], 5, "mrmr"))


for _n, _how in {"sparse_join": {"strategy": "sparse"}, "sparse_frame": {"state": "frame"}, "sparse_lazy": {"lazy": True}}.items():
    query(oracle.greedy_sparse(oracle.token_rows("toxic"), "mrmr", 4), f"greedy_{_n}_mrmr")(lambda s, d, how=_how: scored(greedy.select(workloads.token_set(s, d), 4, "mrmr", **how)))


@query(oracle.greedy(oracle.lines("gate"), GATE, "mrmr", 5))
def greedy_user_criterion(spark, sf_dir):
    """A criterion made by the user (it happens to equal the one above)."""
    mine = Criterion("mine", {"d": Fold(0.0, lambda ops, a, d, e: a + d)}, lambda ops, r, acc, s: r - acc["d"] / s if s else r)
    return scored(greedy.select(workloads.lines(spark, sf_dir), 5, mine))


@query()
def original_and_rewritten(spark, sf_dir):
    """For each criterion, whether the original form makes the same fifth choice as the rewritten one."""
    from .functions.criteria import original_score

    ds = workloads.lines(spark, sf_dir)
    rel = {r["feature"]: r["rel"] for r in relevance.relevance(ds).collect()}
    out, known = [], {}
    for name in ("mim", "mifs", "mrmr", "jmi", "cmi", "cmim", "if", "icap"):
        steps = greedy.select(ds, 5, name).steps
        chosen = [s["feature"] for s in steps[:4]]
        rounds = {}
        for j in chosen:
            if j not in known:
                cells = counts.contingency(ds, ds.features[j])
                known[j] = info.mi_and_cmi(cells).join(info.pair_info(cells), "feature").collect()
            for r in known[j]:
                rounds.setdefault(r["feature"], []).append({"mi": r["mi"], "cmi": r["cmi"], "pair": r["pair_info"], "j_rel": rel[j]})
        given = [ds.features[j] for j in chosen]
        joint = {f: info.cond_mutual_info_set(ds.columns(), ds.features[f], "y", given).first()["cmi"] for f in rel if f not in chosen} if name == "cmi" else {}
        best = max((f for f in rel if f not in chosen), key=lambda f: (round(original_score(name, rel[f], rounds[f], joint=joint.get(f)), 12), -f))
        out.append((name, ds.features[best], steps[4]["name"], best == steps[4]["feature"]))
    return spark.createDataFrame(out, "criterion string, original string, rewritten string, same boolean")


@query(" UNION ALL ".join(f"SELECT '{c}' AS criterion, name, score FROM ({oracle.greedy(oracle.lines('gate'), GATE, c, 3)}) WHERE step = 3" for c in BUILT_IN))
def criteria_registered(spark, sf_dir):
    """The criteria that come with the engine (users may register more), each with its third choice among the line items' features."""
    found = greedy.select_each(workloads.lines(spark, sf_dir), 3, [c for c in criteria() if c in BUILT_IN])
    rows = [(c, s["name"], s["score"]) for c, steps in found.items() for s in steps.steps[2:]]
    return spark.createDataFrame(rows, "criterion string, name string, score double").select("criterion", "name", r6("score").alias("score"))


# --- layout ---------------------------------------------------------------------------------------------------------
@query(f"SELECT CAST(feature AS INT) AS feature, count(*) AS n, CAST(sum(x) AS BIGINT) AS total FROM (WITH {_LONG} SELECT feature, x FROM long) GROUP BY feature")
def feature_blocks(spark, sf_dir):
    """Codes of each feature in the transposed layout: their number and sum."""
    blocks = layout.to_feature_blocks(workloads.lines(spark, sf_dir)).where("feature >= 0")
    return blocks.select("feature", F.explode("codes").alias("x")).groupBy("feature").agg(F.count("*").alias("n"), F.sum("x").alias("total"))


@query(f"SELECT qty, disc, tax, y, count(*) AS n FROM ({_BASE}) GROUP BY ALL")
def blocks_roundtrip(spark, sf_dir):
    ds = workloads.lines(spark, sf_dir).only(["qty", "disc", "tax"])
    return layout.from_feature_blocks(layout.to_feature_blocks(ds), ds.features).groupBy("qty", "disc", "tax", "y").agg(F.count("*").alias("n"))


@query()
def npart_histograms(spark, sf_dir):
    """Partial histograms of each feature with as many partitions as features: two at most."""
    ds = workloads.lines(spark, sf_dir)
    return layout.partial_histograms(layout.to_feature_blocks(ds, len(ds.features)))


@query(f"WITH {oracle.token_rows('toxic')} SELECT name, count(*) AS df, CAST(sum(y) AS BIGINT) AS positives FROM posts JOIN vocab USING (feature) GROUP BY name")
def postings(spark, sf_dir):
    ds = workloads.token_set(spark, sf_dir)
    return relevance.named(ds, ds.postings).groupBy("name").agg(F.count("*").alias("df"), F.sum("y").alias("positives"))


@query(f"WITH {oracle.token_rows('toxic')} SELECT name, floor(rid / 100)::BIGINT AS chunk, count(*) AS entries, min(rid) AS least FROM posts JOIN vocab USING (feature) GROUP BY ALL")
def postings_vectorized(spark, sf_dir):
    ds = workloads.token_set(spark, sf_dir)
    made = relevance.named(ds, layout.vectorized(ds.postings, 100))
    return made.select("name", "chunk", F.size("entries").cast("long").alias("entries"), F.col("entries")[0]["row_id"].alias("least"))


# --- preparation ----------------------------------------------------------------------------------------------------
@query("SELECT CAST(greatest(least(floor((o_totalprice - lo) / (hi - lo) * 16), 15), 0) AS INT) AS bin, count(*) AS n FROM orders, (SELECT min(o_totalprice) AS lo, max(o_totalprice) AS hi FROM orders) GROUP BY ALL")
def discretize_width(spark, sf_dir):
    orders = table(spark, sf_dir, "orders")
    lo, hi = encode.width_bounds(orders, ["o_totalprice"])["o_totalprice"]
    return orders.groupBy(encode.equal_width(F.col("o_totalprice"), lo, hi, 16).alias("bin")).agg(F.count("*").alias("n"))


@query("SELECT CAST(b AS INT) AS bin, count(*) AS n, min(o_totalprice) AS least FROM (SELECT o_totalprice, ntile(10) OVER (ORDER BY o_totalprice, o_orderkey) - 1 AS b FROM orders) GROUP BY b")
def discretize_freq(spark, sf_dir):
    binned = encode.ntile_bins(table(spark, sf_dir, "orders"), "o_totalprice", 10, ["o_orderkey"])
    return binned.groupBy(F.col("o_totalprice_bin").alias("bin")).agg(F.count("*").alias("n"), F.min("o_totalprice").alias("least"))


@query()
def discretize_quantiles(spark, sf_dir):
    """Equal-frequency bins from approximate quantiles of two columns in one pass."""
    binned = encode.equal_frequency(table(spark, sf_dir, "orders"), ["o_totalprice"], 10)
    return binned.groupBy("o_totalprice_bin").agg(F.count("*").alias("n"))


@query("SELECT CAST((l_quantity >= 10)::INT + (l_quantity >= 25)::INT + (l_quantity >= 46)::INT AS INT) AS band, count(*) AS n FROM lineitem GROUP BY ALL")
def explicit_bands(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").groupBy(encode.bands(F.col("l_quantity"), [10, 25, 46]).alias("band")).agg(F.count("*").alias("n"))


@query("SELECT p_brand AS value, CAST(dense_rank() OVER (ORDER BY p_brand) - 1 AS INT) AS code FROM (SELECT DISTINCT p_brand FROM part)")
def dictionary_codes(spark, sf_dir):
    return encode.dictionary(table(spark, sf_dir, "part"), "p_brand")


@query("SELECT name, count(*) AS df FROM (SELECT DISTINCT doc_id, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS name FROM documents) GROUP BY name")
def token_presence(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select(F.explode(encode.tokens(F.col("text"))).alias("name"))
    return docs.groupBy("name").agg(F.count("*").alias("df"))


@query("WITH w AS (SELECT item_id, regexp_extract_all(lower(text), '[a-z]+') AS w FROM benchmark) SELECT gram, count(*) AS n FROM (SELECT unnest(list_transform(range(1, greatest(len(w), 1)), lambda i: w[i] || ' ' || w[i + 1])) AS gram FROM w) GROUP BY gram")
def ngram_counts(spark, sf_dir):
    words = F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0))
    return table(spark, sf_dir, "benchmark").select(F.explode(encode.ngrams(words, 2)).alias("gram")).groupBy("gram").agg(F.count("*").alias("n"))


@query("SELECT CAST(json_extract_string(props, '$.k') AS INT) AS k, count(*) AS n FROM events GROUP BY ALL")
def json_feature(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy(F.from_json("props", "k int")["k"].alias("k")).agg(F.count("*").alias("n"))


@query(f"SELECT {oracle.bucket('l_orderkey')} < 80 AS train, count(*) AS n, CAST(sum(y) AS BIGINT) AS positives FROM ({_BASE}) GROUP BY ALL")
def holdout_counts(spark, sf_dir):
    train, test = sampling.holdout(workloads.lines(spark, sf_dir).df, F.col("l_orderkey"))
    return train.withColumn("train", F.lit(True)).union(test.withColumn("train", F.lit(False))).groupBy("train").agg(F.count("*").alias("n"), F.sum("y").alias("positives"))


@query(f"SELECT count(*) AS n FROM lineitem WHERE {oracle.bucket('l_orderkey', 10_000, 16_807, 5)} < 625")
def ratio_sample(spark, sf_dir):
    return sampling.take_ratio(table(spark, sf_dir, "lineitem"), 1 / 16, F.col("l_orderkey")).agg(F.count("*").alias("n"))


_ROS = f"""b AS (SELECT *, {oracle.bucket('l_orderkey', 1_000_000, 69_621, 7)} AS pick FROM ({oracle.lines('rare')})),
    k AS (SELECT y, count(*) AS c FROM b GROUP BY y), t AS (SELECT y, greatest(1.0, max(c) OVER () * 1.0 / c)::DOUBLE AS r FROM k),
    o AS (SELECT b.*, CAST(floor(r) + CASE WHEN pick < floor((r - floor(r)) * 1000000) THEN 1 ELSE 0 END AS INT) AS copies FROM b JOIN t USING (y))"""


@query(f"WITH {_ROS} SELECT y, CAST(sum(copies) AS BIGINT) AS n FROM o GROUP BY y")
def oversample_counts(spark, sf_dir):
    return sampling.random_oversample(workloads.lines(spark, sf_dir, "rare").df, "y", key=F.col("l_orderkey")).groupBy("y").agg(F.count("*").alias("n"))


_WIDE = " UNION ALL ".join(f"SELECT {i} AS feature, {f} AS x, y, copies FROM o" for i, f in enumerate(GATE))


@query(f"WITH {_ROS}, cells AS (SELECT feature, x, y, sum(copies) AS c FROM ({_WIDE}) GROUP BY ALL), {oracle.relevance_of()} SELECT {oracle._name('feature', GATE)} AS name, round(rel, 6) + 0.0 AS rel FROM rel")
def oversample_relevance(spark, sf_dir):
    """Relevance on the balanced set, replicated as weights: no row is written twice."""
    ds = workloads.lines(spark, sf_dir, "rare")
    return named_relevance(Dataset(sampling.random_oversample(ds.df, "y", key=F.col("l_orderkey"), mode="weight"), ds.features, weight="weight"))


@query(f"WITH b AS ({_BASE}), k AS (SELECT y, count(*) AS c, sum({' + '.join(f'({f} <> 0)::INT' for f in GATE)}) AS z FROM b GROUP BY y) SELECT CAST(sum(c) AS BIGINT) AS rows, CAST(10 AS BIGINT) AS features, count(*) AS classes, round(max(c) / sum(c), 6) AS largest_share, round(sum(z) / (sum(c) * 10), 6) AS density FROM k")
def dataset_summary(spark, sf_dir):
    return _rounded(metrics.dataset_summary(workloads.lines(spark, sf_dir)))


@query(f"WITH {oracle.token_rows('toxic')} SELECT (SELECT count(*) FROM classes) AS rows, (SELECT count(*) FROM vocab) AS features, (SELECT count(DISTINCT y) FROM classes) AS classes, round((SELECT max(c) FROM (SELECT count(*) AS c FROM classes GROUP BY y)) / (SELECT count(*) FROM classes), 6) AS largest_share, round((SELECT count(*) FROM posts) / ((SELECT count(*) FROM classes) * (SELECT count(*) FROM vocab)), 6) AS density")
def sparse_summary(spark, sf_dir):
    return _rounded(metrics.dataset_summary(workloads.token_set(spark, sf_dir)))


def _rounded(df: DataFrame) -> DataFrame:
    return df.select("rows", "features", "classes", F.round("largest_share", 6).alias("largest_share"), F.round("density", 6).alias("density"))


# --- baselines ------------------------------------------------------------------------------------------------------
@query(oracle.chi_square(oracle.lines("gate"), GATE, 5))
def chi_square_rank(spark, sf_dir):
    return baselines.chi_square(workloads.lines(spark, sf_dir), 5)


@query(_MRMR)
def sequential_mrmr(spark, sf_dir):
    steps = baselines.sequential(workloads.lines(spark, sf_dir), 5, "mrmr")
    return spark.createDataFrame([tuple(s[c] for c in ("step", "name", "score", "rel")) for s in steps], "step int, name string, score double, rel double").select("step", "name", r6("score").alias("score"), r6("rel").alias("rel"))


@query()
def forest_importance(spark, sf_dir):
    return baselines.forest_importance(workloads.lines(spark, sf_dir), 5)


_KEY = "((i + 1) * 48271 + 7 * 69621) * 16807 % 2147483647 % 1000003"


@query(f"WITH {oracle.token_rows('toxic')} SELECT CAST(row_number() OVER (ORDER BY {_KEY}, i) AS INT) AS step, name FROM (SELECT CAST(feature AS BIGINT) AS i, name FROM vocab) QUALIFY step <= 5")
def random_features(spark, sf_dir):
    """Five tokens of the labelled documents in an order that only their numbers and the seed decide."""
    chosen = baselines.random_names(workloads.token_set(spark, sf_dir), 5)
    return spark.createDataFrame([(i + 1, n) for i, n in enumerate(chosen)], "step int, name string")


# --- evaluation -----------------------------------------------------------------------------------------------------
def nb_auc(ds: Dataset, features: list[str]) -> DataFrame:
    train, test = sampling.holdout(ds.df, F.col("l_orderkey"))
    model = models.CategoricalNB(features).fit(train)
    return metrics.auc(model.score(test, [])).select(r6("auc").alias("auc"))


query("SELECT auc FROM " + oracle.auc_nb("gate", GATE, "'all' AS ranking"), "auc_all_features")(lambda s, d: nb_auc(workloads.lines(s, d), list(GATE)))
query("SELECT auc FROM " + oracle.auc_nb("noisy", GATE, "'all' AS ranking"), "auc_all_features_noisy")(lambda s, d: nb_auc(workloads.lines(s, d, "noisy"), list(GATE)))


for _t in ("gate", "noisy"):
    # the planted features and the first one alone, whatever a ranking makes of them
    for _n, _f in {"planted": workloads.PLANTED, "best": workloads.PLANTED[:1], "twins": [*workloads.PLANTED[:1], *workloads.TWINS]}.items():
        query("SELECT auc FROM " + oracle.auc_nb(_t, _f, f"'{_n}' AS ranking"), f"auc_{_n}_{_t}")(lambda s, d, t=_t, f=_f: nb_auc(workloads.lines(s, d, t), list(f)))


def fitted_rankings(ds: Dataset, k: int = 5, names=("mim", "mrmr", "cmim")) -> dict[str, list[str]]:
    """The first k features by each criterion on the training rows."""
    train, _ = sampling.holdout(ds.df, F.col("l_orderkey"))
    return {c: greedy.select(Dataset(train, ds.features), k, c).names for c in names}


def _fitted_sweep(spark, sf_dir, target: str) -> DataFrame:
    out = []
    ds = workloads.lines(spark, sf_dir, target)
    for name, ranking in fitted_rankings(ds).items():
        out += [(name, k, ",".join(ranking[:k]), nb_auc(ds, ranking[:k]).first()["auc"]) for k in (1, 2, 3, 5)]
    return spark.createDataFrame(out, "ranking string, k int, features string, auc double")


query(name="auc_by_threshold")(lambda s, d: _fitted_sweep(s, d, "gate"))
query(name="auc_by_threshold_noisy")(lambda s, d: _fitted_sweep(s, d, "noisy"))

_FITS = {"nb": models.naive_bayes, "svm": models.svm, "sgd": lambda rows: models.svm(rows, impl="sgd")}


def classifier_study(spark, sf_dir, workload: str = "noisy", classifier: str = "nb", ks=(1, 2, 3, 5, 10)) -> DataFrame:
    """k, auc and training seconds of a classifier on the first k features by the benchmark criterion on the training rows.

    workload: a target of the line items (all ten features at most), embed (binary class) or a target of the tokens.
    """
    sparse_set, presence = workload in ("toxic", "quality"), None
    if sparse_set:
        ds = workloads.token_set(spark, sf_dir, workload)
        train_set = ds.within(sampling.trains(F.col("row_id")))
    else:
        ds = workloads.embed(spark, sf_dir, binary=True) if workload == "embed" else workloads.lines(spark, sf_dir, workload)
        train, test = sampling.holdout(ds.df, F.col("vec_id" if workload == "embed" else "l_orderkey"))
        train_set = Dataset(train, ds.features)
    found, out = greedy.select(train_set, max(ks), "mrmr"), []
    size = train_set.size if sparse_set else len(ds.features)
    if found.blocks is not None:
        presence = train_set.presence(found.blocks, found.places).persist()
    for k in ks:
        if presence is not None:
            # equal rows come once, as below
            rows = models.restricted(presence, k)
            a, b = (models.present(rows.where(side), k).persist() for side in ("inside", "NOT inside"))
        elif sparse_set:
            rows = models.presence_vectors(ds, [s["feature"] for s in found.steps[:k]])
            a, b = (r.persist() for r in sampling.holdout(rows, F.col("row_id")))
        else:
            names = [s["name"] for s in found.steps[:k]]
            vectors = models.OneHot(train, names)
            # equal rows come once; the batch optimiser scales by the deviation of single rows and keeps them
            a = vectors(train if classifier == "svm" else models.grouped(train, names)).persist()
            b = vectors(models.grouped(test, names)).persist()
        if classifier == "sgd" or classifier == "svm" and presence is not None:
            a = models.packed(a.unpersist()).persist()
        a.count()
        model, seconds = metrics.timed(_FITS[classifier], a)
        ranked = models.scored(model, b)
        area = metrics.auc(ranked.withColumn("score", F.round("score", 10)), weight="weight" if "weight" in ranked.columns else None).first()["auc"]
        out.append((workload, classifier, k, None if area is None else float(area), seconds, metrics.model_size(k, size)))
        a.unpersist(), b.unpersist()
    if presence is not None:
        presence.unpersist()
    return spark.createDataFrame(out, "workload string, classifier string, k int, auc double, train_seconds double, share_kept double")


# training seconds differ from run to run: no SQL; tests hold the models against NumPy and against each other
for _w, _ks in {"noisy": (1, 2, 3, 5, 10), "embed": (10, 25, 50, 64), "toxic": (10, 25, 50, 100), "quality": (10, 25, 50, 100)}.items():
    for _m in ("nb", "svm", "sgd"):
        query(name=f"{_m}_study" + ("" if _w == "noisy" else f"_{_w}"))(lambda s, d, w=_w, m=_m, ks=_ks: classifier_study(s, d, w, m, ks))


@query()
def selection_times(spark, sf_dir):
    """Seconds from the call until k features are ranked, by workload and threshold; reading, packing and counting ahead are in them."""
    sets = {
        "gate": (workloads.lines(spark, sf_dir), (1, 2, 5, 10)), "star": (workloads.star(spark, sf_dir), (10, 24)), "embed": (workloads.embed(spark, sf_dir), (10, 25, 50)),
        "tokens": (workloads.token_set(spark, sf_dir), (10, 25, 50, 100)), "hashed": (workloads.token_set(spark, sf_dir, "quality", ngram=2, buckets=1 << 20), (10, 25, 50, 100)),
    }
    out = []
    for name, (ds, ks) in sets.items():
        found, total = metrics.timed(greedy.select, ds, max(ks), "mrmr")
        out += [(name, k, float(total - sum(found.seconds[k:]))) for k in ks if k <= len(found.steps)]
    return spark.createDataFrame(out, "workload string, k int, seconds double")


@query()
def speedup_table(spark, sf_dir):
    """Sequential and distributed seconds by number of rows, with the largest sizes of the sequential run extrapolated."""
    out, points = [], []
    for ratio in (1 / 80, 1 / 16, 1 / 2, 1.0):
        ds = workloads.lines(spark, sf_dir)
        ds = Dataset(sampling.take_ratio(ds.df, ratio, F.col("l_orderkey")), ds.features)
        _, fast = metrics.timed(greedy.select, ds, 5, "mrmr")
        if len(points) < 2:
            _, slow = metrics.timed(baselines.sequential, ds, 5, "mrmr")
            points.append((ds.n, slow))
        else:
            slow = metrics.extrapolate_linear(points, ds.n)
        out.append((ds.n, float(slow), fast, metrics.speedup(slow, fast), len(out) >= 2))
    return spark.createDataFrame(out, "rows long, sequential double, distributed double, speedup double, estimated boolean")


@query("""WITH p AS (SELECT year(o_orderdate) AS x, count(*)::DOUBLE AS n FROM orders WHERE year(o_orderdate) < 2001 GROUP BY ALL), m AS (SELECT avg(x) AS mx, avg(n) AS mn FROM p),
    l AS (SELECT any_value(mx) AS mx, any_value(mn) AS mn, sum((x - mx) * (n - mn)) / sum((x - mx) * (x - mx)) AS slope FROM p, m) SELECT year, round(mn + slope * (year - mx), 2) + 0.0 AS orders FROM l, (VALUES (2005), (2010)) t(year)""")
def extrapolated_times(spark, sf_dir):
    """Orders of the whole years, the straight line through them being carried on to later ones."""
    orders = table(spark, sf_dir, "orders").select(F.year("o_orderdate").alias("year")).where("year < 2001")
    points = [(r["year"], r["count"]) for r in orders.groupBy("year").count().collect()]
    found = spark.createDataFrame([(x, metrics.extrapolate_linear(points, x)) for x in (2005, 2010)], "year int, orders double")
    return found.select("year", (F.round("orders", 2) + F.lit(0.0)).alias("orders"))


_RANKED = ("mrmr", "mim", "mifs", "jmi", "cmi", "cmim", "icap")


@query(f"""WITH r AS MATERIALIZED ({' UNION ALL '.join(f"SELECT '{c}' AS c, step, name FROM ({oracle.greedy(oracle.lines('gate'), GATE, c, 5)})" for c in _RANKED)}), b AS (SELECT step, name FROM r WHERE c = 'mrmr'),
    o AS (SELECT x.c, count(*) AS n FROM r x JOIN r z ON x.c = z.c AND x.step < z.step JOIN b bx ON bx.name = x.name JOIN b bz ON bz.name = z.name WHERE bx.step > bz.step GROUP BY x.c)
    SELECT r.c AS criterion, count(b.name) / 5.0::DOUBLE AS overlap, CAST(coalesce(any_value(o.n), 0) AS INT) AS distance, count(*) FILTER (r.step <= 3 AND r.name IN ('disc', 'tax', 'qty')) / 3.0::DOUBLE AS recovered
    FROM r LEFT JOIN b ON b.name = r.name LEFT JOIN o ON o.c = r.c GROUP BY r.c""")
def agreement_of_criteria(spark, sf_dir):
    """Overlap and order distance of each criterion's ranking with the benchmark criterion's, and planted features found."""
    ds = workloads.lines(spark, sf_dir)
    ranked = {c: greedy.select(ds, 5, c).names for c in _RANKED}
    rows = [(c, metrics.overlap(r, ranked["mrmr"]), metrics.kendall_distance(r, ranked["mrmr"]), metrics.recovery(r, workloads.PLANTED)) for c, r in ranked.items()]
    return spark.createDataFrame(rows, "criterion string, overlap double, distance int, recovered double")


@query()
def plan_costs(spark, sf_dir):
    """Exchanges, broadcasts and Python steps of a round's plan under each strategy."""
    ds = workloads.lines(spark, sf_dir)
    rows = [(s, *metrics.plan_costs(counts.contingency(ds, "disc", s)).values()) for s in ("explode", "arrow", "gsets", "blocks", "packed")]
    return spark.createDataFrame(rows, "strategy string, exchanges int, broadcasts int, python int")


@query("SELECT name, round(rel, 6) + 0.0 AS rel FROM (VALUES ('a', 0.0), ('b', 0.0), ('c', 0.0), ('copy_a', 0.0)) t(name, rel)")
def tiny_relevance(spark, sf_dir):
    return named_relevance(workloads.tiny(spark))


# --- relational operators -------------------------------------------------------------------------------------------
def _t(spark, sf_dir, *names):
    found = [table(spark, sf_dir, n) for n in names]
    return found[0] if len(found) == 1 else found


@query("SELECT l_orderkey, l_linenumber, CAST(floor(l_quantity) - 1 AS INT) AS qty, CASE WHEN l_discount >= 0.05 THEN 'high' ELSE 'low' END AS level FROM lineitem")
def rel_projection(spark, sf_dir):
    return _t(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", (F.floor("l_quantity") - 1).cast("int").alias("qty"), F.when(F.col("l_discount") >= 0.05, "high").otherwise("low").alias("level"))


@query("SELECT p_partkey, p_brand FROM part WHERE p_size BETWEEN 10 AND 20 AND p_type IN (SELECT DISTINCT p_type FROM part) AND p_brand LIKE 'B%' AND p_name IS NOT NULL AND regexp_matches(p_brand, '[0-9]') AND NOT (p_size IS NOT DISTINCT FROM 15)")
def rel_filter(spark, sf_dir):
    part = _t(spark, sf_dir, "part")
    kept = part.where(F.col("p_size").between(10, 20) & F.col("p_brand").like("B%") & F.col("p_name").isNotNull() & F.col("p_brand").rlike("[0-9]") & ~F.col("p_size").eqNullSafe(15))
    return kept.select("p_partkey", "p_brand")


@query("SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def rel_hash_join(spark, sf_dir):
    customer, nation = _t(spark, sf_dir, "customer", "nation")
    return customer.join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))


@query("SELECT o_orderstatus, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY ALL")
def rel_merge_join(spark, sf_dir):
    line, orders = _t(spark, sf_dir, "lineitem", "orders")
    return line.join(orders.hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderstatus").agg(F.count("*").alias("n"))


@query("SELECT s_suppkey, count(*) AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY ALL")
def rel_shuffle_hash_join(spark, sf_dir):
    line, supplier = _t(spark, sf_dir, "lineitem", "supplier")
    return line.join(supplier.hint("shuffle_hash"), F.col("l_suppkey") == F.col("s_suppkey")).groupBy("s_suppkey").agg(F.count("*").alias("n"))


@query("SELECT a.n_nationkey AS i, b.n_nationkey AS k FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey")
def rel_theta_join(spark, sf_dir):
    nation = _t(spark, sf_dir, "nation").select("n_nationkey")
    a, b = nation.withColumnRenamed("n_nationkey", "i"), nation.withColumnRenamed("n_nationkey", "k")
    return a.join(b, F.col("i") < F.col("k"))


@query("SELECT CAST(floor(l_quantity / 10) AS INT) AS bin, count(*) AS n FROM lineitem WHERE l_quantity >= 0 AND l_quantity < 60 GROUP BY ALL")
def rel_range_join(spark, sf_dir):
    """Values and the intervals they fall into."""
    bounds = spark.range(6).select(F.col("id").cast("int").alias("bin"), (F.col("id") * 10).alias("lo"), (F.col("id") * 10 + 10).alias("hi"))
    line = _t(spark, sf_dir, "lineitem")
    return line.join(F.broadcast(bounds), (F.col("l_quantity") >= F.col("lo")) & (F.col("l_quantity") < F.col("hi"))).groupBy("bin").agg(F.count("*").alias("n"))


@query("""WITH p AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'purchase'), c AS (SELECT user_id, ts, event_id AS c_id FROM events WHERE event_type = 'click')
    SELECT p.event_id, coalesce((SELECT max_by(c_id, (ts, c_id)) FROM c WHERE c.user_id = p.user_id AND (c.ts < p.ts OR (c.ts = p.ts AND c_id < p.event_id))), -1) AS last_click FROM p""")
def rel_asof_join(spark, sf_dir):
    """For each purchase, the user's last click before it: both kinds in one pass over each user's events in order."""
    events = _t(spark, sf_dir, "events").where(F.col("event_type").isin("purchase", "click"))
    before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    click = F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(before)
    return events.withColumn("last_click", click).where("event_type = 'purchase'").select("event_id", F.coalesce("last_click", F.lit(-1)).alias("last_click"))


@query("SELECT count(*) AS n FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def rel_semi_join(spark, sf_dir):
    docs, labels = _t(spark, sf_dir, "documents", "labels")
    return docs.join(labels, "doc_id", "left_semi").agg(F.count("*").alias("n"))


@query("SELECT count(*) AS n FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def rel_anti_join(spark, sf_dir):
    docs, labels = _t(spark, sf_dir, "documents", "labels")
    return docs.join(labels, "doc_id", "left_anti").agg(F.count("*").alias("n"))


@query("SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY ALL")
def rel_outer_join(spark, sf_dir):
    customer, orders = _t(spark, sf_dir, "customer", "orders")
    return customer.join(orders, F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


@query("SELECT coalesce(a.k, b.k) AS k, coalesce(a.n, 0) AS orders, coalesce(b.n, 0) AS lines FROM (SELECT month(o_orderdate) AS k, count(*) AS n FROM orders WHERE o_orderstatus = 'F' GROUP BY 1) a FULL JOIN (SELECT month(l_shipdate) AS k, count(*) AS n FROM lineitem WHERE l_quantity = 50 GROUP BY 1) b ON a.k = b.k")
def rel_full_outer_join(spark, sf_dir):
    orders, line = _t(spark, sf_dir, "orders", "lineitem")
    a = orders.where("o_orderstatus = 'F'").groupBy(F.month("o_orderdate").cast("long").alias("k")).agg(F.count("*").alias("orders"))
    b = line.where("l_quantity = 50").groupBy(F.month("l_shipdate").cast("long").alias("k")).agg(F.count("*").alias("lines"))
    return a.join(b, "k", "full").select("k", F.coalesce("orders", F.lit(0)).alias("orders"), F.coalesce("lines", F.lit(0)).alias("lines"))


@query("SELECT r_name, o_orderstatus, n FROM region CROSS JOIN (SELECT o_orderstatus, count(*) AS n FROM orders GROUP BY ALL)")
def rel_cross_join(spark, sf_dir):
    region, orders = _t(spark, sf_dir, "region", "orders")
    return region.crossJoin(F.broadcast(orders.groupBy("o_orderstatus").agg(F.count("*").alias("n")))).select("r_name", "o_orderstatus", "n")


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty FROM lineitem GROUP BY ALL")
def rel_hash_aggregate(spark, sf_dir):
    return _t(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"))


@query("SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY ALL")
def rel_object_aggregate(spark, sf_dir):
    return _t(spark, sf_dir, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("names"))


@query("SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY ALL")
def rel_distinct_aggregate(spark, sf_dir):
    return _t(spark, sf_dir, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


@query("SELECT l_returnflag, l_linestatus, CAST(grouping(l_returnflag, l_linestatus) AS BIGINT) AS level, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def rel_grouping_sets(spark, sf_dir):
    return _t(spark, sf_dir, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.grouping_id().cast("long").alias("level"), F.count("*").alias("n"))


@query("SELECT l_returnflag, count(*) AS n FROM lineitem GROUP BY ROLLUP (l_returnflag)")
def rel_rollup(spark, sf_dir):
    return _t(spark, sf_dir, "lineitem").rollup("l_returnflag").agg(F.count("*").alias("n"))


@query("SELECT l_returnflag, count(*) FILTER (l_linestatus = 'F') AS f, count(*) FILTER (l_linestatus = 'O') AS o FROM lineitem GROUP BY ALL")
def rel_pivot(spark, sf_dir):
    wide = _t(spark, sf_dir, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count(F.lit(1)))
    return wide.select("l_returnflag", F.col("F").alias("f"), F.col("O").alias("o"))


@query("SELECT l_returnflag, kind, n FROM (SELECT l_returnflag, count(*) FILTER (l_linestatus = 'F') AS f, count(*) FILTER (l_linestatus = 'O') AS o FROM lineitem GROUP BY ALL) UNPIVOT (n FOR kind IN (f, o))")
def rel_unpivot(spark, sf_dir):
    return rel_pivot(spark, sf_dir).unpivot(["l_returnflag"], ["f", "o"], "kind", "n")


@query("SELECT o_orderpriority, count(*) FILTER (o_totalprice > 200000) AS dear, CAST(sum(CASE WHEN o_orderstatus = 'F' THEN 1 ELSE 0 END) AS BIGINT) AS done FROM orders GROUP BY ALL")
def rel_filtered_aggregate(spark, sf_dir):
    return _t(spark, sf_dir, "orders").groupBy("o_orderpriority").agg(F.count_if(F.col("o_totalprice") > 200000).alias("dear"), F.sum(F.when(F.col("o_orderstatus") == "F", 1).otherwise(0)).alias("done"))


@query("SELECT o_orderpriority, arg_max(o_orderkey, (o_totalprice, -o_orderkey)) AS best FROM orders GROUP BY ALL")
def rel_arg_max(spark, sf_dir):
    best = F.max(F.struct("o_totalprice", (-F.col("o_orderkey")).alias("k")))
    return _t(spark, sf_dir, "orders").groupBy("o_orderpriority").agg(best.alias("b")).select("o_orderpriority", (-F.col("b.k")).alias("best"))


_WIN = "OVER (PARTITION BY n_regionkey ORDER BY n_name)"


@query(f"SELECT n_name, CAST(row_number() {_WIN} AS INT) AS rn, CAST(rank() {_WIN} AS INT) AS rk, CAST(dense_rank() {_WIN} AS INT) AS dr, CAST(ntile(2) {_WIN} AS INT) AS nt, round(percent_rank() {_WIN}, 6) AS pr, round(cume_dist() {_WIN}, 6) AS cd FROM nation")
def rel_ranking_window(spark, sf_dir):
    w = Window.partitionBy("n_regionkey").orderBy("n_name")
    return _t(spark, sf_dir, "nation").select("n_name", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(2).over(w).alias("nt"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


@query(f"SELECT n_name, lag(n_name) {_WIN} AS lag, lead(n_name) {_WIN} AS lead, first_value(n_name) {_WIN} AS first, nth_value(n_name, 2) {_WIN} AS second FROM nation")
def rel_analytic_window(spark, sf_dir):
    w = Window.partitionBy("n_regionkey").orderBy("n_name")
    return _t(spark, sf_dir, "nation").select("n_name", F.lag("n_name").over(w).alias("lag"), F.lead("n_name").over(w).alias("lead"), F.first("n_name").over(w).alias("first"), F.nth_value("n_name", 2).over(w).alias("second"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS recent FROM events")
def rel_frame_window(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-3, 0)
    return _t(spark, sf_dir, "events").select("event_id", F.count("*").over(w).alias("recent"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
def rel_top_k(spark, sf_dir):
    return _t(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10)


@query("SELECT o_orderpriority, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) <= 3")
def rel_top_per_group(spark, sf_dir):
    w = Window.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return _t(spark, sf_dir, "orders").withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("o_orderpriority", "o_orderkey")


@query("SELECT c_nationkey AS k FROM customer WHERE c_acctbal > 0 INTERSECT SELECT s_nationkey FROM supplier WHERE s_acctbal > 0")
def rel_intersect(spark, sf_dir):
    customer, supplier = _t(spark, sf_dir, "customer", "supplier")
    return customer.where("c_acctbal > 0").select(F.col("c_nationkey").alias("k")).intersect(supplier.where("s_acctbal > 0").select("s_nationkey"))


@query("SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
def rel_except_all(spark, sf_dir):
    customer, supplier = _t(spark, sf_dir, "customer", "supplier")
    return customer.select(F.col("c_nationkey").alias("k")).exceptAll(supplier.select("s_nationkey"))


@query("SELECT k, count(*) AS n FROM (SELECT c_nationkey AS k FROM customer UNION ALL SELECT s_nationkey FROM supplier) GROUP BY k")
def rel_union(spark, sf_dir):
    customer, supplier = _t(spark, sf_dir, "customer", "supplier")
    return customer.select(F.col("c_nationkey").alias("k")).union(supplier.select("s_nationkey")).groupBy("k").agg(F.count("*").alias("n"))


@query("SELECT count(*) AS n FROM (SELECT DISTINCT text FROM documents)")
def rel_dedup(spark, sf_dir):
    return _t(spark, sf_dir, "documents").select("text").dropDuplicates().agg(F.count("*").alias("n"))


@query("SELECT count(*) AS n FROM orders o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM orders) AND EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o.o_orderkey AND l_quantity >= 46)")
def rel_subqueries(spark, sf_dir):
    for name in ("orders", "lineitem"):
        table(spark, sf_dir, name).createOrReplaceTempView(f"fs_{name}")
    return spark.sql("SELECT count(*) AS n FROM fs_orders o WHERE o_totalprice > (SELECT avg(o_totalprice) FROM fs_orders) AND EXISTS (SELECT 1 FROM fs_lineitem WHERE l_orderkey = o.o_orderkey AND l_quantity >= 46)")


@query("WITH RECURSIVE t AS (SELECT c_custkey AS k, c_mktsegment FROM customer WHERE c_custkey = 1 UNION ALL SELECT c.c_custkey, c.c_mktsegment FROM t JOIN customer c ON c.c_custkey = t.k * 2) SELECT k, c_mktsegment FROM t")
def rel_recursive_cte(spark, sf_dir):
    """From the first customer to the one of twice the key, as long as there is one."""
    table(spark, sf_dir, "customer").createOrReplaceTempView("fs_customer")
    return spark.sql("WITH RECURSIVE t AS (SELECT c_custkey AS k, c_mktsegment FROM fs_customer WHERE c_custkey = 1 UNION ALL SELECT c.c_custkey, c.c_mktsegment FROM t JOIN fs_customer c ON c.c_custkey = t.k * 2) SELECT k, c_mktsegment FROM t")


@query()
def rel_stratified_sample(spark, sf_dir):
    return _t(spark, sf_dir, "lineitem").sampleBy("l_returnflag", {"A": 0.1, "N": 0.05, "R": 0.1}, seed=7).groupBy("l_returnflag").agg(F.count("*").alias("n"))


@query("SELECT count(*) AS n FROM lineitem")
def rel_repartition(spark, sf_dir):
    return _t(spark, sf_dir, "lineitem").select("l_orderkey").repartitionByRange(8, "l_orderkey").agg(F.count("*").alias("n"))


@query("SELECT p_partkey, CAST(CASE WHEN p_retailprice < 900 THEN 0 WHEN p_retailprice >= 1000 THEN 6 ELSE floor((p_retailprice - 900) / 20) + 1 END AS BIGINT) AS w, p_size % 7 AS m, CAST(NULL AS DOUBLE) AS d FROM part")
def scalar_math(spark, sf_dir):
    return _t(spark, sf_dir, "part").select("p_partkey", F.width_bucket("p_retailprice", F.lit(900.0), F.lit(1000.0), F.lit(5)).alias("w"), F.pmod("p_size", F.lit(7)).alias("m"), F.try_divide(F.col("p_size"), F.lit(0)).cast("double").alias("d"))


@query("SELECT n_nationkey, lower(n_name) AS low, length(n_name) AS len, translate(n_name, 'AE', 'xy') AS tr, levenshtein(n_name, 'FRANCE') AS d FROM nation")
def scalar_string(spark, sf_dir):
    return _t(spark, sf_dir, "nation").select("n_nationkey", F.lower("n_name").alias("low"), F.length("n_name").cast("long").alias("len"), F.translate("n_name", "AE", "xy").alias("tr"), F.levenshtein("n_name", F.lit("FRANCE")).cast("long").alias("d"))


@query("SELECT o_orderkey, year(o_orderdate) AS y, isodow(o_orderdate) - 1 AS wd, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS m FROM orders")
def scalar_date(spark, sf_dir):
    return _t(spark, sf_dir, "orders").select("o_orderkey", F.year("o_orderdate").cast("long").alias("y"), F.weekday("o_orderdate").cast("long").alias("wd"), F.date_format(F.trunc("o_orderdate", "month"), "yyyy-MM-dd").alias("m"))


@query("SELECT vec_id, round(list_sum(list_transform(embedding[1:8], lambda x: x::DOUBLE * x::DOUBLE)), 6) AS s, len(list_filter(embedding, lambda x: x > 0)) AS pos FROM embeddings")
def scalar_array(spark, sf_dir):
    v = F.col("embedding").cast("array<double>")
    return _t(spark, sf_dir, "embeddings").select("vec_id", F.round(F.aggregate(F.slice(v, 1, 8), F.lit(0.0), lambda s, x: s + x * x), 6).alias("s"), F.size(F.filter(v, lambda x: x > 0)).cast("long").alias("pos"))


@query("SELECT 1.0::DOUBLE AS one, 0.0::DOUBLE AS none, 1.0::DOUBLE AS given")
def sql_information(spark, sf_dir):
    """The registered SQL functions on hand-made tables: a bit of information, none, and a bit given the third variable."""
    udf.register_functions(spark)
    return spark.sql("SELECT mi_from_counts(array(4, 0, 0, 4), 2, 2) AS one, mi_from_counts(array(2, 2, 2, 2), 2, 2) AS none, cmi_from_counts(array(2, 0, 0, 2, 0, 2, 2, 0), 2, 2, 2) AS given")


#: All features but the segment itself.
_INSIDE = [f for f in GATE if f != "rf"]
_BY_FLAG = f"SELECT rf, step, name, round(score, 6) + 0.0 AS score FROM ({oracle.greedy_by(oracle.lines('gate'), 'rf', (0, 1, 2), _INSIDE, 'mrmr', 3)})"


@query(f"SELECT step, name, score FROM ({_BY_FLAG})")
def sql_selection_by_segment(spark, sf_dir):
    """A selection for each return flag through the table function, one partition each; rows with equal codes come once, with their number."""
    udf.register_functions(spark)
    rows = workloads.lines(spark, sf_dir).df
    rows.groupBy(*_INSIDE, "rf", "y").agg(F.count("*").alias("rows")).createOrReplaceTempView("fs_gate")
    return spark.sql("SELECT step, name, round(score, 6) + 0.0D AS score FROM select_features(TABLE(fs_gate) PARTITION BY (rf), 'y', 3, 'mrmr', 'rows')")


@query(_BY_FLAG)
def selection_by_segment(spark, sf_dir):
    """The same by grouped pandas: segment, step, name, score."""
    import pandas as pd

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        steps = baselines.sequential_select(pdf, _INSIDE, "y", 3, "mrmr")
        return pd.DataFrame([(key[0], s["step"], s["name"], s["score"]) for s in steps], columns=["rf", "step", "name", "score"])

    found = workloads.lines(spark, sf_dir).df.select("rf", *_INSIDE, "y").groupBy("rf").applyInPandas(run, "rf int, step int, name string, score double")
    return found.withColumn("score", r6("score"))


@query()
def generated_rows(spark, sf_dir):
    """Relevance of the synthetic source's first features."""
    generator.register(spark)
    rows = spark.read.format("sparse_rows").options(rows=2000, features=5000, nonzeros=12, partitions=4).load()
    ds = layout.to_postings(rows.select("row_id", F.transform("features", lambda f: f.cast("string")).alias("t")), "t", rows.select("row_id", "y"))
    return named_relevance(ds)


# --- sources, sinks and the pipeline stage ---------------------------------------------------------------------------
def _path(spark, name: str) -> str:
    return f"{folder(spark)}/{name}-{uuid.uuid4().hex}"


_GATE_RELEVANCE = oracle.relevance(oracle.lines("gate"), GATE)


@query(_GATE_RELEVANCE)
def libsvm_relevance(spark, sf_dir):
    """The line items written as LibSVM text, read back and counted as sparse data."""
    path = _path(spark, "libsvm")
    ds = workloads.lines(spark, sf_dir)
    tables.to_vector(ds.df, GATE).select(F.col("y").cast("double").alias("label"), "features").write.format("libsvm").save(path)
    rows = saved(tables.libsvm(spark, path, len(GATE)).withColumn("row_id", F.monotonically_increasing_id()), "rows")
    found = relevance.relevance(layout.from_vectors(rows, "features", "label"))
    return found.select(F.element_at(F.array(*[F.lit(f) for f in GATE]), F.col("feature").cast("int") + 1).alias("name"), r6("rel").alias("rel"))


@query(_GATE_RELEVANCE)
def maps_relevance(spark, sf_dir):
    """Rows as maps from feature names to codes."""
    ds = workloads.lines(spark, sf_dir)
    codes = F.map_from_arrays(F.array(*[F.lit(f) for f in GATE]), F.array(*[F.col(f) for f in GATE]))
    rows = saved(ds.df.select(codes.alias("codes"), "y").withColumn("row_id", F.monotonically_increasing_id()), "rows")
    return named_relevance(layout.from_maps(rows, "codes", "y"))


@query(" UNION ALL ".join(f"SELECT '{f}' AS format, n_regionkey, count(*) AS n, sum(n_nationkey)::BIGINT AS keys, min(n_name) AS first FROM nation GROUP BY ALL" for f in ("csv", "json", "orc", "parquet")))
def read_formats(spark, sf_dir):
    """A table written and read back in every file format, with an explicit schema where the format has none."""
    nation, out = table(spark, sf_dir, "nation"), None
    for fmt in ("csv", "json", "orc", "parquet"):
        path = _path(spark, fmt)
        nation.write.format(fmt).save(path)
        back = tables.read(spark, fmt, path, nation.schema if fmt in ("csv", "json") else None)
        one = back.groupBy("n_regionkey").agg(F.count("*").alias("n"), F.sum("n_nationkey").cast("long").alias("keys"), F.min("n_name").alias("first")).select(F.lit(fmt).alias("format"), "*")
        out = one if out is None else out.union(one)
    return out


@query(f"SELECT rf, count(*) AS n, CAST(sum(y) AS BIGINT) AS positives FROM ({_BASE}) GROUP BY rf")
def write_partitioned(spark, sf_dir):
    """The coded rows in folders by return flag, as a sink for a reduced data set."""
    path = _path(spark, "reduced")
    tables.write(workloads.lines(spark, sf_dir).df.select("disc", "tax", "qty", "rf", "y"), path, partition_by=["rf"])
    return tables.read(spark, "parquet", path).groupBy("rf").agg(F.count("*").alias("n"), F.sum("y").alias("positives"))


@query("SELECT o_orderpriority, count(*) AS n, 0 AS exchanges FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderpriority")
def bucketed_join(spark, sf_dir):
    """Two bucketed tables joined on their bucket column: neither side is exchanged."""
    sides = {}
    for name, key, more in (("lineitem", "l_orderkey", ["l_quantity"]), ("orders", "o_orderkey", ["o_orderpriority"])):
        made = f"fs_{name}_{uuid.uuid4().hex}"
        sides[name] = tables.write_bucketed(table(spark, sf_dir, name).select(key, *more), made, 4, [key], path=_path(spark, made))
    joined = sides["lineitem"].hint("merge").join(sides["orders"], F.col("l_orderkey") == F.col("o_orderkey"))
    return joined.groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.lit(metrics.plan_costs(joined)["exchanges"]).alias("exchanges"))


@query("SELECT r_name, count(*) AS n FROM region JOIN nation ON n_regionkey = r_regionkey GROUP BY r_name")
def registered_views(spark, sf_dir):
    tables.register_views(spark, sf_dir, ("region", "nation"))
    return spark.sql("SELECT r_name, count(*) AS n FROM region JOIN nation ON n_regionkey = r_regionkey GROUP BY r_name")


@query(f"SELECT unnest([{', '.join(repr(f) for f in GATE)}]) AS name")
def constant_dropped(spark, sf_dir):
    """Features with more than one value, a constant column and an empty one being left out."""
    rows = workloads.lines(spark, sf_dir).df.withColumns({"always": F.lit(3), "never": F.lit(None).cast("int")})
    return spark.createDataFrame([(f,) for f in encode.drop_constant(rows, [*GATE, "always", "never"])], "name string")


@query(f"SELECT step, name, score FROM ({_MRMR})")
def estimator_selection(spark, sf_dir):
    """Selection as a stage of an ML pipeline, on a vector column."""
    from .operators.estimator import InfoSelector

    rows = tables.to_vector(workloads.lines(spark, sf_dir).df, GATE).select("features", F.col("y").alias("label"))
    model = InfoSelector(k=5, criterion="mrmr").fit(rows)
    found = [(i + 1, GATE[f], s) for i, (f, s) in enumerate(zip(model.getOrDefault("indices"), model.getOrDefault("scores")))]
    return spark.createDataFrame(found, "step int, name string, score double").select("step", "name", r6("score").alias("score"))


# --- streaming ------------------------------------------------------------------------------------------------------
def _events_dir(spark, sf_dir: str) -> str:
    """The events as a folder of files in the shared folder, which is what the file source reads."""
    path = f"{folder(spark)}/events-{uuid.uuid4().hex}"
    table(spark, sf_dir, "events").repartitionByRange(4, "ts").write.parquet(path)
    return path


def _in_order(spark, sf_dir: str, parts: list[str]) -> str:
    """The events as one file for each condition, in this order of arrival."""
    path = f"{folder(spark)}/events-{uuid.uuid4().hex}"
    for k, part in enumerate(parts):
        table(spark, sf_dir, "events").where(part).coalesce(1).write.mode("append").parquet(path)
        if k + 1 < len(parts):
            time.sleep(0.05)  # files are taken by their time
    return path


def _run(df: DataFrame, mode: str) -> DataFrame:
    """Runs a stream over what is there: appended rows and complete results go to files, updates (small) to a table in memory."""
    name = f"fs_{uuid.uuid4().hex}"
    spark = df.sparkSession
    path = f"{folder(spark)}/{name}"
    writer = df.writeStream.outputMode(mode).option("checkpointLocation", f"{path}-checkpoint").trigger(availableNow=True)
    last: list[int] = []

    def whole(batch: DataFrame, number: int) -> None:
        """Each batch has the whole result, so the last one counts; one that is repeated replaces itself."""
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")
        last[:] = [number]

    match mode:
        case "append":
            writer = writer.format("parquet").option("path", path)
        case "complete":
            writer = writer.foreachBatch(whole)
        case _:
            writer = writer.format("memory").queryName(name)
    writer.start().awaitTermination()
    if mode == "complete":
        return spark.read.schema(df.schema).parquet(f"{path}/batch={last[0]}") if last else spark.createDataFrame([], df.schema)
    return spark.read.schema(df.schema).parquet(path) if mode == "append" else spark.table(name)


_EVENT_LONG = f"WITH {oracle.unpivoted(oracle.events().replace('AS y FROM events', 'AS y, event_type, ts FROM events').replace('dense_rank() OVER (ORDER BY event_type) - 1', '0'), oracle.event_features()).replace('SELECT rid, ', 'SELECT event_type, ts, rid, ')}"


@query(f"{_EVENT_LONG} SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS start, CAST(feature AS INT) AS feature, x, event_type, count(*) AS c FROM long GROUP BY ALL")
def stream_window_counts(spark, sf_dir):
    stream = streaming.events(spark, _events_dir(spark, sf_dir))
    return _run(streaming.window_counts(stream), "complete").withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss"))


@query(f"{_EVENT_LONG} SELECT strftime(s, '%Y-%m-%d %H:%M:%S') AS start, CAST(feature AS INT) AS feature, x, event_type, count(*) AS c FROM (SELECT *, unnest([date_trunc('day', ts) + to_hours(CAST(floor(hour(ts) / 6.0) * 6 AS BIGINT)) - to_hours(6 * k) for k in range(4)]) AS s FROM long) GROUP BY ALL")
def stream_sliding_counts(spark, sf_dir):
    stream = streaming.events(spark, _events_dir(spark, sf_dir))
    return _run(streaming.window_counts(stream, "1 day", "6 hours"), "complete").withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss"))


@query("SELECT count(*) AS sessions, CAST(sum(c) AS BIGINT) AS events FROM (SELECT user_id, s, count(*) AS c FROM (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events)) GROUP BY ALL)")
def stream_session_counts(spark, sf_dir):
    stream = streaming.events(spark, _events_dir(spark, sf_dir))
    return _run(streaming.session_counts(stream), "complete").agg(F.count("*").alias("sessions"), F.sum("c").alias("events"))


@query(oracle.relevance(oracle.events(), oracle.event_features()))
def stream_running_ranking(spark, sf_dir):
    base = f"{folder(spark)}/running-{uuid.uuid4().hex}"
    streaming.running_ranking(streaming.events(spark, _events_dir(spark, sf_dir), 1), f"{base}/cells", f"{base}/checkpoint").awaitTermination()
    name = F.element_at(F.array(*[F.lit(f) for f in workloads.EVENTS]), F.col("feature") + 1)
    return streaming.ranking(spark, f"{base}/cells").select(name.alias("name"), r6("rel").alias("rel"))


#: Days on which the batches of the drift queries begin.
_CUTS = (1, 9, 17, 25, 40)
_BATCHES = [f"day(ts) >= {a} AND day(ts) < {b}" for a, b in zip(_CUTS, _CUTS[1:])]
_BATCH_SQL = f"CASE {' '.join(f'WHEN day(ts) < {b} THEN {k}' for k, b in enumerate(_CUTS[1:]))} END"


@query(f"""WITH e AS (SELECT user_id % 16 AS user_bucket, {_BATCH_SQL} AS b, value FROM events), s AS (SELECT user_bucket, b, count(*) AS n, sum(value) AS t FROM e GROUP BY ALL),
    r AS (SELECT *, sum(n) OVER w AS total_n, sum(t) OVER w AS total_t FROM s WINDOW w AS (PARTITION BY user_bucket ORDER BY b))
    SELECT CAST(user_bucket AS INT) AS user_bucket, CAST(total_n AS BIGINT) AS n, round(total_t / total_n, 4) + 0.0 AS mean, round(CASE WHEN total_n = n THEN 0 ELSE t / n - (total_t - t) / (total_n - n) END, 4) + 0.0 AS change FROM r""")
def stream_drift(spark, sf_dir):
    found = _run(streaming.drift(streaming.events(spark, _in_order(spark, sf_dir, _BATCHES), 1)), "update")
    return found.select("user_bucket", "n", (F.round("mean", 4) + F.lit(0.0)).alias("mean"), (F.round("change", 4) + F.lit(0.0)).alias("change"))


def _drift_sql() -> str:
    base = oracle.events().replace("AS y FROM events", f"AS y, {_BATCH_SQL} AS b FROM events")
    rows = " UNION ALL ".join(f"SELECT b, {i} AS f, {f} AS x, y FROM base" for i, f in enumerate(oracle.event_features()))
    return f"""WITH base AS MATERIALIZED ({base}), long AS ({rows}), own AS (SELECT b, f, x, y, count(*) AS c FROM long GROUP BY ALL),
        cells AS MATERIALIZED (SELECT f + 10 * b AS feature, x, y, c FROM own UNION ALL SELECT l.f + 10 * k.b + 100, x, y, CAST(sum(c) AS BIGINT) FROM own l JOIN (SELECT DISTINCT b FROM own) k ON l.b < k.b GROUP BY ALL), {oracle.relevance_of()}
        SELECT CAST(n.feature // 10 AS INT) AS batch, {oracle._name('n.feature % 10', oracle.event_features())} AS name, round(n.rel, 6) + 0.0 AS rel, round(p.rel, 6) + 0.0 AS before, round(n.rel - p.rel, 6) + 0.0 AS change
        FROM rel n LEFT JOIN rel p ON p.feature = n.feature + 100 WHERE n.feature < 100"""


@query(_drift_sql())
def stream_relevance_drift(spark, sf_dir):
    """How relevance moves from batch to batch."""
    base = f"{folder(spark)}/drift-{uuid.uuid4().hex}"
    streaming.relevance_drift(streaming.events(spark, _in_order(spark, sf_dir, _BATCHES), 1), base, f"{base}/checkpoint").awaitTermination()
    name = F.element_at(F.array(*[F.lit(f) for f in workloads.EVENTS]), F.col("feature") + 1)
    return spark.read.parquet(f"{base}/drift").select("batch", name.alias("name"), r6("rel").alias("rel"), r6("before").alias("before"), r6("change").alias("change"))


@query("""WITH m AS (SELECT max(ts) - INTERVAL 2 HOUR AS w FROM events WHERE day(ts) >= 10)
    SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, event_type, count(*) AS c FROM events, m WHERE day(ts) >= 10 AND date_trunc('day', ts) + INTERVAL 1 DAY <= w GROUP BY ALL""")
def stream_late_data(spark, sf_dir):
    """Days below 10 arrive last.  Rows are late by the watermark that the batch before began with, so these are left out; windows it has passed are appended."""
    stream = streaming.events(spark, _in_order(spark, sf_dir, ["day(ts) >= 10 AND day(ts) < 20", "day(ts) >= 20", "day(ts) < 10"]), 1)
    counted = stream.withWatermark("ts", "2 hours").groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("c"))
    return _run(counted.select(F.col("window.start").alias("start"), "event_type", "c"), "append").select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "c")


@query("SELECT count(*) AS n FROM events")
def stream_dedup(spark, sf_dir):
    """Every file twice: events are counted once."""
    path = _events_dir(spark, sf_dir)
    table(spark, sf_dir, "events").repartitionByRange(4, "ts").write.mode("append").parquet(path)
    return _run(streaming.deduplicated(streaming.events(spark, path), "40 days"), "append").agg(F.count("*").alias("n"))


@query("SELECT c_mktsegment, count(*) AS n FROM events LEFT JOIN customer ON user_id = c_custkey GROUP BY ALL")
def stream_static_join(spark, sf_dir):
    users = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    stream = streaming.with_users(streaming.events(spark, _events_dir(spark, sf_dir)), users)
    return _run(stream.groupBy("c_mktsegment").agg(F.count("*").alias("n")), "complete")
