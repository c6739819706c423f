"""Registered queries over the given tables, each with a DuckDB twin where SQL can express it.

A prepared collection is kept per session, folder and workload: the measured joins exclude preparation.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from setsim.functions import sql as sql_surface
from setsim.functions import theory
from setsim.functions.bitmap import BitmapSpec, attach, bit_string
from setsim.functions.spec import SimSpec
from setsim.operators import joins
from setsim.operators.order import Collection, prepare, prepare_pair
from setsim.plans import experiments, metrics, planner
from setsim.scratch import Scratch
from setsim.sources.workloads import WORKLOADS, drawn, synth, table
from setsim.streaming.sets import stream_sets

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
_PREPARED: dict[tuple, Collection | tuple] = {}

# set collections in SQL ------------------------------------------------------------------------------------------------------

_WORD = r"[^ \t\n\r\f\v]+"
_ARRAYS = {
    "part_name_q2": ("p_partkey", "list_transform(range(1, length(p_name)), lambda i: substring(lower(p_name), i, 2))", "part"),
    "doc_words": ("doc_id", f"regexp_extract_all(lower(text), '{_WORD}')", "documents"),
    "doc_q3": ("doc_id", "list_transform(range(1, length(text) - 1), lambda i: substring(lower(text), i, 3))", "documents"),
    "page_words": ("page_id", "regexp_extract_all(lower(html), '[a-z0-9]+')", "pages"),
    "emb_pos": ("vec_id", "list_transform(list_filter(range(1, len(embedding) + 1), lambda i: embedding[i] > 0), lambda i: CAST(i AS VARCHAR))", "embeddings"),
    "doc_shingles": ("doc_id", "list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2])", f"(SELECT doc_id, regexp_extract_all(lower(text), '{_WORD}') w FROM documents)"),
    "bench_shingles": ("item_id", "list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2])", f"(SELECT item_id, regexp_extract_all(lower(text), '{_WORD}') w FROM benchmark)"),
    "conv_words": ("conv_id", f"regexp_extract_all(lower(text), '{_WORD}')", "conversations"),
}
SETS_SQL = {k: f"SELECT DISTINCT CAST({sid} AS BIGINT) AS sid, unnest({arr}) AS tok FROM {src}" for k, (sid, arr, src) in _ARRAYS.items()} | {
    "order_parts": "SELECT DISTINCT l_orderkey AS sid, CAST(l_partkey AS VARCHAR) AS tok FROM lineitem",
    "cust_brands": "SELECT DISTINCT o_custkey AS sid, p_brand AS tok FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN part ON l_partkey = p_partkey",
    "cust_parts": "SELECT DISTINCT o_custkey AS sid, CAST(l_partkey AS VARCHAR) AS tok FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "supp_parts": "SELECT DISTINCT l_suppkey AS sid, CAST(l_partkey AS VARCHAR) AS tok FROM lineitem",
    "turn_words": f"SELECT DISTINCT CAST(conv_id * 1000 + turn AS BIGINT) AS sid, unnest(regexp_extract_all(lower(text), '{_WORD}')) AS tok FROM conversations",
    "user_evt_hour": "SELECT DISTINCT CAST(user_id AS BIGINT) AS sid, event_type || '@' || strftime(ts, '%Y-%m-%d %H') AS tok FROM events",
    "user_evt_dow": "SELECT DISTINCT CAST(user_id AS BIGINT) AS sid, event_type || '@' || CAST(dayofweek(ts) AS VARCHAR) AS tok FROM events",
}


def _accepts(measure: str, p: int, q: int) -> str:
    return {"overlap": f"o >= {p}", "jaccard": f"o * {q} >= {p} * (n + m - o)", "cosine": f"o * o * {q * q} >= {p * p} * n * m", "dice": f"2 * o * {q} >= {p} * (n + m)"}[measure]


_SIM = {"overlap": "CAST(o AS DOUBLE)", "jaccard": "CAST(o AS DOUBLE) / (n + m - o)", "cosine": "CAST(o AS DOUBLE) / sqrt(CAST(n * m AS DOUBLE))", "dice": "CAST(2 * o AS DOUBLE) / (n + m)"}


def pairs_sql(workload: str, measure: str, threshold: str, right: str | None = None) -> str:
    """All similar pairs by counting common tokens."""
    spec = SimSpec.of(measure, threshold)
    own = right is None
    return f"""WITH r AS ({SETS_SQL[workload]}), s AS ({"SELECT * FROM r" if own else SETS_SQL[right]}),
rn AS (SELECT sid, count(*) AS n FROM r GROUP BY sid), sn AS (SELECT sid, count(*) AS m FROM s GROUP BY sid),
c AS (SELECT r.sid AS id_l, s.sid AS id_r, count(*) AS o FROM r JOIN s ON r.tok = s.tok {"AND r.sid < s.sid" if own else ""} GROUP BY r.sid, s.sid)
SELECT id_l, id_r, CAST(n AS INTEGER) AS n_l, CAST(m AS INTEGER) AS n_r, CAST(o AS INTEGER) AS overlap, {_SIM[measure]} AS sim
FROM c JOIN rn ON rn.sid = id_l JOIN sn ON sn.sid = id_r WHERE {_accepts(measure, spec.num, spec.den)}"""


_RANKED = "s AS ({sets}), v AS (SELECT tok, count(*) AS df, row_number() OVER (ORDER BY count(*), tok) - 1 AS rank FROM s GROUP BY tok)"


def bitmap_sql(workload: str, b: int, variant: str) -> str:
    """Bits from slot loads, without bit arithmetic."""
    head = f"WITH {_RANKED.format(sets=SETS_SQL[workload])}, load AS (SELECT sid, rank % {b} AS k, count(*) AS c FROM s JOIN v USING (tok) GROUP BY 1, 2), ids AS (SELECT DISTINCT sid FROM s)"
    if variant == "probe":
        return f"""{head}, laps AS (SELECT ids.sid, i.k AS t, coalesce(c, 0) AS c FROM ids CROSS JOIN range({2 * b}) i(k) LEFT JOIN load ON load.sid = ids.sid AND load.k = i.k % {b}),
sums AS (SELECT sid, t, c, sum(c - 1) OVER (PARTITION BY sid ORDER BY t) AS total FROM laps),
carried AS (SELECT sid, t, c, total - least(0, min(total) OVER (PARTITION BY sid ORDER BY t)) AS carry FROM sums),
bits AS (SELECT sid, t, CASE WHEN coalesce(lag(carry) OVER (PARTITION BY sid ORDER BY t), 0) + c >= 1 THEN '1' ELSE '0' END AS bit FROM carried)
SELECT sid, string_agg(bit, '' ORDER BY t DESC) AS bits FROM bits WHERE t >= {b} GROUP BY sid"""
    on = "coalesce(c, 0) > 0" if variant == "or" else "coalesce(c, 0) % 2 = 1"
    return f"{head} SELECT ids.sid, string_agg(CASE WHEN {on} THEN '1' ELSE '0' END, '' ORDER BY i.k DESC) AS bits FROM ids CROSS JOIN range({b}) i(k) LEFT JOIN load ON load.sid = ids.sid AND load.k = i.k GROUP BY ids.sid"


def candidates_sql(workload: str, spec: SimSpec, variant: str, b: int = 64) -> str:
    """Prefix-and-length candidates of a Jaccard self-join: ``kept`` by the filter (no cutoff), ``placed`` by their positions."""
    p, q = spec.num, spec.den
    need = f"({p} * (c.n + c.m) + {p + q - 1}) // {p + q}"
    if b == 64 and variant != "probe":
        bits, distance = f"SELECT sid, bit_{variant}(1::UBIGINT << CAST(rank % 64 AS UBIGINT)) AS w FROM t GROUP BY sid", "bit_count(xor(x.w, y.w))"
    else:
        bits, distance = f"SELECT sid, bits AS w FROM ({bitmap_sql(workload, b, variant)})", "hamming(x.w, y.w)"
    return f"""WITH {_RANKED.format(sets=SETS_SQL[workload])}, t AS (SELECT sid, rank, count(*) OVER (PARTITION BY sid) AS n, row_number() OVER (PARTITION BY sid ORDER BY rank) AS i FROM s JOIN v USING (tok)),
p AS (SELECT * FROM t WHERE i <= n - (({p} * n + {q - 1}) // {q}) + 1), w AS ({bits}),
h AS (SELECT a.sid AS r, b.sid AS s, a.n AS n, b.n AS m, a.i AS i, b.i AS j FROM p a JOIN p b ON a.rank = b.rank AND (b.n, b.sid) < (a.n, a.sid) AND b.n * {q} >= {p} * a.n),
c AS (SELECT r, s, n, m, min(i) AS i, min(j) AS j FROM h GROUP BY r, s, n, m),
k AS (SELECT c.*, (c.n + c.m - {distance}) // 2 >= {need} AS kept, least(c.n - c.i, c.m - c.j) + 1 >= {need} AS placed FROM c JOIN w x ON x.sid = c.r JOIN w y ON y.sid = c.s)"""


def ratio_sql(workload: str, threshold: str, variant: str, b: int = 64, more: str = "") -> str:
    return f"{candidates_sql(workload, SimSpec.of('jaccard', threshold), variant, b)} SELECT count(*) AS candidates, count(*) FILTER (NOT kept) AS pruned, round(count(*) FILTER (NOT kept) / nullif(count(*), 0), 6) AS ratio{more} FROM k"


def union_sql(parts) -> str:
    return " UNION ALL ".join(f"SELECT * FROM ({x})" for x in parts)


#: Thresholds of the ratio and join series per collection; dense collections start where their candidates stay below 10^7.
RATIO_SERIES = {"order_parts": ("0.5", "0.6", "0.7", "0.75", "0.8", "0.85", "0.9", "0.95"), "part_name_q2": ("0.7", "0.8", "0.9"), "cust_brands": ("0.7", "0.8", "0.9"), "user_evt_dow": ("0.5", "0.6", "0.7", "0.8", "0.9", "0.95"), "doc_words": ("0.7", "0.8", "0.9"), "doc_q3": ("0.8", "0.9"), "page_words": ("0.5", "0.6", "0.7", "0.8", "0.9"), "emb_pos": ("0.5", "0.6", "0.7")}
JOIN_SERIES = {"order_parts": ("0.5", "0.7", "0.95"), "part_name_q2": ("0.85", "0.95"), "cust_brands": ("0.85", "0.95"), "user_evt_dow": ("0.6", "0.75", "0.9"), "doc_words": ("0.75", "0.85"), "doc_q3": ("0.85", "0.95"), "page_words": ("0.6", "0.75", "0.9"), "emb_pos": ("0.5", "0.6")}

# registration ----------------------------------------------------------------------------------------------------------------


def collection(spark: SparkSession, sf_dir: str, workload: str) -> Collection:
    key = (spark.sparkContext.applicationId, sf_dir, workload)
    if key not in _PREPARED:
        _PREPARED[key] = prepare(WORKLOADS[workload](spark, sf_dir))
    return _PREPARED[key]


def collection_pair(spark: SparkSession, sf_dir: str, left: str, right: str) -> tuple[Collection, Collection]:
    key = (spark.sparkContext.applicationId, sf_dir, left, right)
    if key not in _PREPARED:
        _PREPARED[key] = prepare_pair(WORKLOADS[left](spark, sf_dir), WORKLOADS[right](spark, sf_dir))
    return _PREPARED[key]


def register(name: str, query: Query, oracle: str | None = None) -> None:
    QUERIES[name] = query
    if oracle:
        ORACLES[name] = oracle


def _join(name: str, workload: str, threshold: str, method: str, measure: str = "jaccard", right: str | None = None, **options) -> None:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        a, b = (collection(spark, sf_dir, workload), None) if right is None else collection_pair(spark, sf_dir, workload, right)
        return joins.join_collections(a, b, SimSpec.of(measure, threshold), method, **options)

    register(name, run, pairs_sql(workload, measure, threshold, right))


SHORT = {"naive": "naive", "pfxl": "prefix_length", "pfxlp": "prefix_positional", "pfxlps": "prefix_suffix", "ell2": "ell_prefix", "grp": "grouped_prefix", "block": "block"}
_tag = lambda t: "t" + t.split(".")[1].ljust(2, "0") if "." in t else "t" + t

for _short, _method in SHORT.items():
    _extra = {"ell": 2} if _short == "ell2" else {}
    for _t in ("0.5", "0.8"):
        _join(f"{_short}_order_parts_{_tag(_t)}", "order_parts", _t, _method, **_extra)
        if _short != "naive":
            _join(f"{_short}_order_parts_{_tag(_t)}_hbf", "order_parts", _t, _method, bitmap=BitmapSpec(), **_extra)
for _t in ("0.6", "0.7", "0.75", "0.85", "0.9", "0.95"):
    _join(f"pfxl_order_parts_{_tag(_t)}_hbf", "order_parts", _t, "prefix_length", bitmap=BitmapSpec())
for _ell in (1, 3, "adaptive"):
    _join(f"ell{_ell}_order_parts_t50_hbf", "order_parts", "0.5", "ell_prefix", ell=_ell, bitmap=BitmapSpec())
_join("ell2_order_parts_t50_hbf_first", "order_parts", "0.5", "ell_prefix", ell=2, bitmap=BitmapSpec(), hbf_levels="first")
for _how in ("array", "minrank", "distinct"):
    _join(f"pfxl_order_parts_t80_{_how}", "order_parts", "0.8", "prefix_length", dedup=_how)
for _at in ("pre", "post"):
    _join(f"pfxl_order_parts_t80_hbf_{_at}", "order_parts", "0.8", "prefix_length", bitmap=BitmapSpec(), hbf_at=_at)
for _v in ("or", "xor", "probe"):
    _join(f"pfxl_order_parts_t70_{_v}", "order_parts", "0.7", "prefix_length", bitmap=BitmapSpec(_v, 64))
for _v in ("merge_stop", "relational"):
    _join(f"verify_{_v}_order_parts_t80", "order_parts", "0.8", "prefix_length", verify=_v)
_join("verify_bitset_user_evt_t80", "user_evt_dow", "0.8", "prefix_length", verify="bitset", universe=64)
_join("naive_nested_loop_user_evt_t80", "user_evt_dow", "0.8", "naive", form="nested_loop")
_join("block_cap2048_emb_pos_t50", "emb_pos", "0.5", "block", bitmap=BitmapSpec("xor", 64, cutoff=None), cap=2048)
_join("block_expr_emb_pos_t50", "emb_pos", "0.5", "block", bitmap=BitmapSpec("xor", 64, cutoff=None), kernel="expr")
for _b in (192, 512, 2048):
    _join(f"block_doc_words_t70_b{_b}", "doc_words", "0.7", "block", bitmap=BitmapSpec("xor", _b, cutoff=None))
for _w, _t in (("part_name_q2", "0.9"), ("cust_brands", "0.9"), ("user_evt_dow", "0.8"), ("doc_words", "0.7"), ("doc_q3", "0.9"), ("page_words", "0.7"), ("emb_pos", "0.5"), ("doc_shingles", "0.8")):
    _join(f"pfxl_{_w}_{_tag(_t)}", _w, _t, "prefix_length")
    _join(f"pfxl_{_w}_{_tag(_t)}_hbf", _w, _t, "prefix_length", bitmap=BitmapSpec("auto", 512 if _w in ("doc_words", "page_words", "doc_shingles", "doc_q3") else 64))
    _join(f"pfxlp_{_w}_{_tag(_t)}_hbf", _w, _t, "prefix_positional", bitmap=BitmapSpec("auto", 128))
_join("grp_part_name_q2_t90_hbf", "part_name_q2", "0.9", "grouped_prefix", bitmap=BitmapSpec())
_join("ell2_user_evt_dow_t80_hbf", "user_evt_dow", "0.8", "ell_prefix", ell=2, bitmap=BitmapSpec())
_join("pfxlps_page_words_t70", "page_words", "0.7", "prefix_suffix")
for _m, _t in (("cosine", "0.8"), ("dice", "0.8"), ("overlap", "3")):
    _join(f"{_m}_order_parts", "order_parts", _t, "prefix_positional", measure=_m, bitmap=BitmapSpec())
    _join(f"{_m}_ell2_order_parts", "order_parts", _t, "ell_prefix", measure=_m, ell=2)
_join("cosine_cust_brands_t95", "cust_brands", "0.95", "prefix_length", measure="cosine", bitmap=BitmapSpec())
for _t in ("5", "10", "20"):
    _join(f"rs_bench_overlap{_t}", "doc_shingles", _t, "prefix_length", measure="overlap", right="bench_shingles")
_join("rs_bench_overlap10_hbf", "doc_shingles", "10", "prefix_positional", measure="overlap", right="bench_shingles", bitmap=BitmapSpec("xor", 1024))
for _w in ("cust_parts", "supp_parts", "conv_words", "turn_words", "user_evt_hour"):
    _join(f"control_{_w}_t50", _w, "0.5", "prefix_length", bitmap=BitmapSpec())
_join("pfxl_order_parts_t80_xx64", "order_parts", "0.8", "prefix_length", bitmap=BitmapSpec("xor", 64, hash="xx64"))
_join("pfxlp_order_parts_t60_kernel", "order_parts", "0.6", "prefix_positional", bitmap=BitmapSpec("xor", 64), hbf_at="kernel")
_join("pfxl_order_parts_t80_size_key", "order_parts", "0.8", "prefix_length", bitmap=BitmapSpec(), size_key=True, hot_df=20)
_join("ell2_emb_pos_t50_size_key", "emb_pos", "0.5", "ell_prefix", ell=2, bitmap=BitmapSpec(), size_key=True, hot_df=100)
_join("grp_order_parts_t80_collapse", "order_parts", "0.8", "grouped_prefix", bitmap=BitmapSpec(), collapse=True)


def _profiles() -> None:
    for w in ("order_parts", "part_name_q2", "cust_brands", "user_evt_dow", "doc_words", "doc_q3", "page_words", "emb_pos", "doc_shingles"):
        sizes = f"WITH s AS ({SETS_SQL[w]}), z AS (SELECT sid, count(*) AS n FROM s GROUP BY sid)"
        register(f"profile_{w}", lambda spark, d, w=w: metrics.collection_profile(WORKLOADS[w](spark, d)), f"{sizes} SELECT count(*) AS sets, max(n) AS max_n, round(avg(n), 6) AS avg_n, CAST(quantile_cont(n, 0.5) AS DOUBLE) AS median_n, (SELECT count(DISTINCT tok) FROM s) AS tokens FROM z")
        register(f"size_hist_{w}", lambda spark, d, w=w: metrics.size_histogram(WORKLOADS[w](spark, d)), f"{sizes} SELECT n, count(*) AS sets FROM z GROUP BY n")
        register(f"token_hist_{w}", lambda spark, d, w=w: metrics.token_histogram(WORKLOADS[w](spark, d)), f"WITH s AS ({SETS_SQL[w]}), v AS (SELECT tok, count(*) AS df FROM s GROUP BY tok) SELECT df, count(*) AS tokens FROM v GROUP BY df")
    register("vocab_order_parts", lambda spark, d: collection(spark, d, "order_parts").vocab, f"WITH {_RANKED.format(sets=SETS_SQL['order_parts'])} SELECT tok, df, CAST(rank AS INTEGER) AS rank FROM v")


def _bitmaps() -> None:
    for w, b in (("order_parts", 64), ("page_words", 256)):
        for v in ("or", "xor", "probe"):
            def run(spark, d, w=w, b=b, v=v):
                bits = BitmapSpec(v, b)
                return attach(collection(spark, d, w).sets, bits).select("sid", bit_string(bits.columns, b).alias("bits"))

            register(f"bitmap_{v}_{w}_b{b}", run, bitmap_sql(w, b, v))
    for w, t, v in (("order_parts", "0.5", "xor"), ("order_parts", "0.8", "xor"), ("order_parts", "0.8", "or"), ("page_words", "0.7", "xor")):
        spec = SimSpec.of("jaccard", t)
        register(f"prune_ratio_{w}_{_tag(t)}_{v}", lambda spark, d, w=w, v=v, spec=spec: metrics.prune_ratio(collection(spark, d, w), spec, BitmapSpec(v, 64, cutoff=None)), f"{candidates_sql(w, spec, v)} SELECT count(*) AS candidates, count(*) FILTER (NOT kept) AS pruned, round(count(*) FILTER (NOT kept) / count(*), 6) AS ratio FROM k")
    order, pages = "order_parts", "page_words"
    for name, w, t, shapes in (("prune_ratio_by_variant", order, "0.5", [(v, 64) for v in ("or", "xor", "probe")]), ("prune_ratio_by_width", pages, "0.7", [("xor", b) for b in (64, 128, 256, 512)]),
                               ("prune_shapes_user_evt_dow", "user_evt_dow", "0.8", [(v, b) for v in ("or", "xor", "probe") for b in (16, 32, 64)]), ("prune_shapes_part_name_q2", "part_name_q2", "0.8", [(v, b) for v in ("or", "xor") for b in (16, 32)]), ("prune_shapes_doc_words", "doc_words", "0.8", [(v, 512) for v in ("or", "xor")])):
        register(name, lambda spark, d, w=w, t=t, shapes=shapes: experiments.ratios_by_shape(collection(spark, d, w), t, shapes), union_sql(ratio_sql(w, t, v, b, f", '{v}' AS variant, {b} AS b") for v, b in shapes))
    for w, ts in RATIO_SERIES.items():
        bits = BitmapSpec("xor", 64, cutoff=None)
        register(f"prune_series_{w}", lambda spark, d, w=w, ts=ts: experiments.ratios({w: collection(spark, d, w)}, ts, bits), union_sql(ratio_sql(w, t, "xor", 64, f", '{w}' AS input, '{t}' AS threshold") for t in ts))
    for name, w, t in (("precision_by_size", order, "0.5"), *((f"precision_{w}_{_tag(t)}", w, t) for w in (pages, "user_evt_dow") for t in ("0.5", "0.6", "0.7", "0.8"))):
        spec = SimSpec.of("jaccard", t)
        register(name, lambda spark, d, w=w, spec=spec: metrics.precision_by_size(collection(spark, d, w), spec), f"""{candidates_sql(w, spec, "xor")}, o AS (SELECT k.r, k.s, k.n, k.m, count(*) AS o FROM k JOIN t x ON x.sid = k.r JOIN t y ON y.sid = k.s AND x.rank = y.rank WHERE kept GROUP BY ALL)
SELECT CAST(n AS INTEGER) AS n, count(*) AS unpruned, count(*) FILTER ({_accepts("jaccard", spec.num, spec.den)}) AS similar, round(count(*) FILTER ({_accepts("jaccard", spec.num, spec.den)}) / count(*), 6) AS precision FROM o GROUP BY n""")
    half = SimSpec.of("jaccard", "0.5")
    register("stage_counts", lambda spark, d: metrics.stage_counts(collection(spark, d, order), half, BitmapSpec("xor", 64, cutoff=None)), f"""{candidates_sql(order, half, "xor")}
SELECT (SELECT count(*) FROM h) AS hits, count(*) AS candidates, count(*) AS tests, count(*) FILTER (NOT kept) AS pruned, count(*) FILTER (kept) AS verified, (SELECT count(*) FROM ({pairs_sql(order, "jaccard", "0.5")})) AS similar FROM k""")
    for w, b in ((order, 64), (pages, 256)):
        register(f"variant_distance_{w}", lambda spark, d, w=w, b=b: metrics.variant_distance(collection(spark, d, w), b), f"""WITH {_RANKED.format(sets=SETS_SQL[w])}, load AS (SELECT sid, rank % {b} AS slot, count(*) AS c FROM s JOIN v USING (tok) GROUP BY 1, 2),
per AS (SELECT sid, sum(c) AS n, count(*) FILTER (c % 2 = 0) AS bits FROM load GROUP BY sid) SELECT CAST(n AS INTEGER) AS n, count(*) AS sets, round(avg(bits), 6) AS bits FROM per GROUP BY n""")
    register("naive_tests_order_parts", lambda spark, d: metrics.naive_tests(collection(spark, d, order)), f"SELECT count(*) AS sets, count(*) * (count(*) - 1) // 2 AS tests FROM (SELECT DISTINCT sid FROM ({SETS_SQL[order]}))")
    for w, ts in JOIN_SERIES.items():
        base = pairs_sql(w, "jaccard", ts[0])
        counts = " UNION ALL ".join(f"SELECT '{t}' AS threshold, count(*) FILTER ({ok}) AS pairs, CAST(coalesce(sum(overlap) FILTER ({ok}), 0) AS BIGINT) AS overlap FROM p" for t in ts for ok in [_accepts("jaccard", SimSpec.of("jaccard", t).num, SimSpec.of("jaccard", t).den)])
        register(f"join_series_{w}", lambda spark, d, w=w, ts=ts: experiments.result_sizes(collection(spark, d, w), ts), f"WITH p AS (SELECT *, overlap AS o, n_l AS n, n_r AS m FROM ({base})), c AS ({counts}) SELECT threshold, method, form, pairs, overlap FROM c, (VALUES ('ELL'), ('PFX-L'), ('GRP'), ('PFX-LP')) x(method), (VALUES ('orig'), ('hbf')) y(form)")
    nothing = "SELECT CAST(0 AS BIGINT) AS id_l, CAST(0 AS BIGINT) AS id_r, 0 AS n_l, 0 AS n_r, 0 AS overlap, CAST(0 AS DOUBLE) AS sim WHERE false"
    for kind in ("uniform", "zipf"):
        register(f"synth_{kind}_lost_pairs", lambda spark, d, kind=kind: _lost_in_synth(spark, kind), nothing)
    register("recall_lost_pairs", lambda spark, d: metrics.lost_pairs(collection(spark, d, "order_parts"), SimSpec.of("jaccard", "0.5"), "prefix_length", bitmap=BitmapSpec()), nothing)


def _lost_in_synth(spark: SparkSession, kind: str) -> DataFrame:
    """Pairs of a generated collection that the filtered prefix join misses (none)."""
    return metrics.lost_pairs(prepare(synth(spark, kind, 1500)), SimSpec.of("jaccard", "0.5"), "prefix_positional", bitmap=BitmapSpec())


def _theory() -> None:
    share = "(2 * CAST(tau AS DOUBLE) / (1 + CAST(tau AS DOUBLE)))"
    bound = "CASE variant WHEN 'or' THEN n - b * (pow(1 - 1.0::DOUBLE / b, n) - pow(1 - 1.0::DOUBLE / b, 2 * n)) WHEN 'xor' THEN n - b::DOUBLE / 4 * (1 - pow(1 - 2.0::DOUBLE / b, 2 * n)) ELSE least(n * n / b::DOUBLE, n) END"
    # on the sizes of the sets of parts per customer
    sizes = lambda spark, d: metrics.size_histogram(WORKLOADS["cust_parts"](spark, d))
    hist = f"z AS (SELECT size, count(*) AS sets FROM (SELECT sid, count(*) AS size FROM ({SETS_SQL['cust_parts']}) GROUP BY sid) GROUP BY size)"
    register("cutoff_table", lambda spark, d: theory.cutoff_table(sizes(spark, d)), f"""WITH {hist}, g AS (SELECT * FROM (VALUES ('or'), ('xor'), ('probe')) v(variant), (VALUES (64), (256), (1024), (4096)) w(b), (VALUES ('0.5'), ('0.6'), ('0.7'), ('0.8'), ('0.9')) t(tau)),
e AS (SELECT variant, b, tau, n, {bound} AS bound FROM g, range(1, 40000) r(n)),
x AS (SELECT variant, b, tau, min(n) - 1 AS c FROM e WHERE bound > {share} * n GROUP BY variant, b, tau)
SELECT variant, b, tau, CAST(c AS INTEGER) AS cutoff, c / b::DOUBLE AS relative, CAST(coalesce((SELECT sum(sets) FROM z WHERE size <= c), 0) AS BIGINT) AS covered FROM x""")
    register("expected_bound_curve", lambda spark, d: theory.bound_curve(sizes(spark, d)), f"""WITH {hist}, g AS (SELECT variant, CAST(size AS INTEGER) AS n, sets, 64 AS b FROM (VALUES ('or'), ('xor'), ('probe')) v(variant), z), e AS (SELECT variant, n, sets, {bound} / n AS y FROM g)
SELECT variant, n, sets, round(y, 9) AS share, round(y / (2 - y), 9) AS jaccard FROM e""")
    for v in ("or", "xor", "probe"):
        register(f"monte_carlo_{v}", lambda spark, d, v=v: theory.simulation_agrees(table(spark, d, "events").select(F.col("event_id").cast("long").alias("key")), v), f"""WITH w AS (SELECT count(*) AS runs FROM (SELECT floor(event_id / 256) AS run FROM events GROUP BY run HAVING count(DISTINCT event_id) = 256)),
g AS (SELECT '{v}' AS variant, 64 AS b, n FROM (VALUES (4), (8), (16), (32), (64), (128)) x(n)) SELECT variant, b, n, runs * (128 // n) * 4 AS trials, round({bound}, 6) AS expected, CASE WHEN runs > 0 THEN true END AS agrees FROM g, w""")
    draw = "CAST('0x' || substr(md5(CAST(event_id AS VARCHAR)), 1, 8) AS BIGINT) / 4294967296.0::DOUBLE"
    for kind, mean, token in (("uniform", 10, f"floor({draw} * 220)"), ("zipf", 50, f"floor(pow(101584.0::DOUBLE, {draw})) - 1")):
        register(f"synth_{kind}_profile", lambda spark, d, kind=kind: metrics.collection_profile(drawn(spark, d, kind)), f"""WITH s AS (SELECT DISTINCT floor(event_id / {mean}) AS sid, {token} AS tok FROM events WHERE event_id IS NOT NULL), z AS (SELECT sid, count(*) AS n FROM s GROUP BY sid)
SELECT count(*) AS sets, max(n) AS max_n, round(avg(n), 6) AS avg_n, CAST(quantile_cont(n, 0.5) AS DOUBLE) AS median_n, (SELECT count(DISTINCT tok) FROM s) AS tokens FROM z""")


def _around() -> None:
    words = ("doc_words", "0.7")
    pairs = lambda spark, d: joins.join_collections(collection(spark, d, words[0]), None, SimSpec.of("jaccard", words[1]), "prefix_length", bitmap=BitmapSpec("auto", 512))
    base = pairs_sql("doc_words", "jaccard", "0.7")
    ids = f"p AS ({base}), ids AS (SELECT id_l AS sid FROM p UNION SELECT id_r FROM p), every AS (SELECT DISTINCT sid FROM ({SETS_SQL['doc_words']}))"
    register("semi_docs_with_twin", lambda spark, d: joins.twins(collection(spark, d, "doc_words").sets, pairs(spark, d)).select("sid"), f"WITH {ids} SELECT sid FROM every WHERE sid IN (SELECT sid FROM ids)")
    register("anti_docs_unique", lambda spark, d: joins.without_twin(collection(spark, d, "doc_words").sets, pairs(spark, d)).select("sid"), f"WITH {ids} SELECT sid FROM every WHERE sid NOT IN (SELECT sid FROM ids)")
    register("top_pairs", lambda spark, d: joins.top_pairs(pairs(spark, d), 20), f"SELECT * FROM ({base}) ORDER BY sim DESC, overlap DESC, id_l, id_r LIMIT 20")
    register("top_partners", lambda spark, d: joins.top_partners(pairs(spark, d), 2), f"""WITH p AS ({base}), b AS (SELECT id_l AS id, id_r AS partner, overlap, sim FROM p UNION ALL SELECT id_r, id_l, overlap, sim FROM p)
SELECT id, partner, overlap, sim, CAST(row_number() OVER (PARTITION BY id ORDER BY sim DESC, partner) AS INTEGER) AS place FROM b QUALIFY place <= 2""")
    register("clusters", lambda spark, d: joins.components(pairs(spark, d)), f"""WITH RECURSIVE p AS ({base}), e AS (SELECT id_l AS a, id_r AS b FROM p UNION SELECT id_r, id_l FROM p),
reach AS (SELECT a AS node, b AS other FROM e UNION SELECT r.node, e.b FROM reach r JOIN e ON r.other = e.a) SELECT node, least(node, min(other)) AS component FROM reach GROUP BY node""")

    def dup_labels(spark, d):
        l = table(spark, d, "labels")  # noqa: E741
        a = l.select(F.col("doc_id").alias("id_l"), F.col("quality").alias("q_l"), F.col("toxic").alias("x_l"))
        b = l.select(F.col("doc_id").alias("id_r"), F.col("quality").alias("q_r"), F.col("toxic").alias("x_r"))
        return pairs(spark, d).join(a, "id_l").join(b, "id_r").select("id_l", "id_r", "sim", "q_l", "q_r", "x_l", "x_r", ((F.col("q_l") != F.col("q_r")) | (F.col("x_l") != F.col("x_r"))).alias("differ"))

    register("dup_labels", dup_labels, f"SELECT id_l, id_r, sim, a.quality AS q_l, b.quality AS q_r, a.toxic AS x_l, b.toxic AS x_r, a.quality <> b.quality OR a.toxic <> b.toxic AS differ FROM ({base}) p JOIN labels a ON a.doc_id = id_l JOIN labels b ON b.doc_id = id_r")

    def by_sql(spark, d):
        spec = SimSpec.of("jaccard", "0.8")
        sql_surface.register(spark)
        sql_surface.create_views(collection(spark, d, "order_parts"), "order_parts", spec, BitmapSpec("xor", 64))
        return spark.sql("""WITH c AS (SELECT DISTINCT a.sid AS sid_r, b.sid AS sid_s, a.n AS n_r, b.n AS n_s FROM postings_order_parts a JOIN postings_order_parts b ON a.rank = b.rank AND a.sid < b.sid AND least(a.n, b.n) * 5 >= 4 * greatest(a.n, b.n)),
k AS (SELECT c.* FROM c JOIN sketch_order_parts x ON x.sid = sid_r JOIN sketch_order_parts y ON y.sid = sid_s WHERE hbf_bound(n_r, n_s, hbf_distance(x.w0, y.w0)) >= sim_need('jaccard', 4, 5, n_r, n_s))
SELECT sid_r AS id_l, sid_s AS id_r, sim_jaccard(x.toks, y.toks) AS sim FROM k JOIN sets_order_parts x ON x.sid = sid_r JOIN sets_order_parts y ON y.sid = sid_s WHERE sim_jaccard(x.toks, y.toks) >= 0.8D""")

    register("sql_join_order_parts", by_sql, f"SELECT id_l, id_r, sim FROM ({pairs_sql('order_parts', 'jaccard', '0.8')})")

    def slots(spark, d):
        sql_surface.register(spark)
        collection(spark, d, "order_parts").sets.createOrReplaceTempView("sets_for_slots")
        return spark.sql("SELECT slot, CAST(sum(load) AS BIGINT) AS load FROM sets_for_slots, LATERAL slots_of(toks, 64) GROUP BY slot")

    register("sql_slot_loads", slots, f"WITH {_RANKED.format(sets=SETS_SQL['order_parts'])} SELECT CAST(rank % 64 AS INTEGER) AS slot, count(*) AS load FROM s JOIN v USING (tok) GROUP BY 1")


def _measures() -> None:
    inputs, ts = ("order_parts", "user_evt_dow"), ("0.5", "0.8")

    def runs(spark, d) -> DataFrame:
        """A table of runs whose cost is the number of pairs to verify."""
        return Scratch(spark, "runs").save(experiments.verified_pairs({w: collection(spark, d, w) for w in inputs}, ts), "runs")

    one = lambda w, t, m, rule: f"{candidates_sql(w, SimSpec.of('jaccard', t), 'xor')} SELECT '{w}' AS input, '{m}' AS method, '{t}' AS threshold, CAST(count(*) AS DOUBLE) AS cost_orig, CAST(count(*) FILTER (kept) AS DOUBLE) AS cost_hbf FROM k WHERE {rule}"
    table_ = "WITH r AS (" + union_sql(one(w, t, m, rule) for w in inputs for t in ts for m, rule in (("PFX-L", "true"), ("PFX-LP", "placed"))) + "), i AS (SELECT *, (cost_orig / cost_hbf - 1) * 100 AS gain FROM r)"
    mean = "round(avg(gain), 6)"
    register("measures_cube", lambda spark, d: metrics.mean_improvement(runs(spark, d)), f"{table_} SELECT method, input, threshold, {mean} AS mean_improvement, count(*) AS runs FROM i GROUP BY GROUPING SETS ((method, threshold), (input, threshold), ())")
    columns = ", ".join(f"round(avg(gain) FILTER (threshold = '{t}'), 6) AS \"{t}\"" for t in ts)
    register("measures_by_threshold", lambda spark, d: metrics.by_threshold(metrics.mean_improvement(runs(spark, d)), "method"), f"{table_} SELECT method, {columns} FROM i GROUP BY method")
    register("measures_totals", lambda spark, d: metrics.totals(runs(spark, d)), f"{table_} SELECT method, sum(cost_orig) AS orig, sum(cost_hbf) AS hbf, round((1 - sum(cost_hbf) / sum(cost_orig)) * 100, 6) AS saved FROM r GROUP BY method")
    long = "l AS (SELECT input, threshold, method, 'orig' AS form, cost_orig AS s FROM r UNION ALL SELECT input, threshold, method, 'hbf', cost_hbf FROM r), p AS (SELECT *, rank() OVER (PARTITION BY input, threshold, form ORDER BY s) AS a, rank() OVER (PARTITION BY input, threshold ORDER BY s) AS b FROM l)"
    register("measures_wins", lambda spark, d: metrics.wins(runs(spark, d)), f"{table_}, {long} SELECT method, form, count(*) FILTER (a = 1) AS wins_in_form, count(*) FILTER (b = 1) AS wins_overall FROM p GROUP BY method, form")
    register("measures_share_improved", lambda spark, d: metrics.share_improved(runs(spark, d)), f"{table_}, b AS (SELECT min(cost_orig) AS o, min(cost_hbf) AS h FROM r GROUP BY input, threshold) SELECT (SELECT round(avg(CAST(cost_hbf < cost_orig AS INT)), 6) FROM r) AS runs_improved, (SELECT round(avg(CAST(h < o AS INT)), 6) FROM b) AS inputs_improved")

    def choice(spark, d):
        p = planner.plan(collection(spark, d, "order_parts"), SimSpec.of("jaccard", "0.8"))
        return spark.createDataFrame([(p.method, p.bitmap.b, p.dedup, str(p.ell), p.expected_hits)], "method string, b int, dedup string, ell string, expected_hits long")

    register("planner_choice", choice, f"WITH s AS ({SETS_SQL['order_parts']}), v AS (SELECT count(*) AS df FROM s GROUP BY tok) SELECT 'prefix_length' AS method, 64 AS b, 'array' AS dedup, '1' AS ell, CAST(sum(df * (df - 1)) // 2 AS BIGINT) AS expected_hits FROM v")


def stream_user_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All events through a stream of daily sets per user, drained, as a table."""
    scratch = Scratch(spark, "stream")
    source = spark.read.parquet(f"{sf_dir}/events.parquet")
    events = spark.readStream.schema(source.schema).parquet(f"{sf_dir}/events.parque[t]")  # a pattern: the path may be one file
    sets = stream_sets(events, watermark="")
    target = f"{scratch.base}/sets"
    done = sets.writeStream.outputMode("complete").foreachBatch(lambda batch, i: batch.write.mode("overwrite").parquet(target)).option("checkpointLocation", f"{scratch.base}/state").trigger(availableNow=True).start()
    done.awaitTermination()
    return spark.read.parquet(target).select("key", F.date_format("window_start", "yyyy-MM-dd").alias("day"), F.array_join("tokens", ",").alias("tokens"), "n")


register("stream_user_sets", stream_user_sets, "SELECT user_id AS key, strftime(ts, '%Y-%m-%d') AS day, string_agg(DISTINCT event_type, ',' ORDER BY event_type) AS tokens, CAST(count(DISTINCT event_type) AS INTEGER) AS n FROM events GROUP BY 1, 2")
_profiles()
_bitmaps()
_theory()
_around()
_measures()
