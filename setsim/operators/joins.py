"""The similarity joins and the operators around them.

========================  ==========================================================================================
``naive``                 token equi-join and count (``form="relational"``) or nested loop; no filter
``prefix_length``         prefix filter, length filter
``prefix_positional``     the same and the positional filter
``prefix_suffix``         the same and the suffix filter
``ell_prefix``            prefixes longer by ell - 1 tokens, pairs need ell common prefix tokens; ``ell="adaptive"``
``grouped_prefix``        positional prefix join of groups of sets with equal size and prefix, then expansion
``block``                 all pairs of bitmaps within the length filter, tokens afterwards
========================  ==========================================================================================

Every join gives the same exact result with and without a bitmap filter. A ``Collection`` (see ``order.prepare``) is
what they work on; ``similarity_join`` also takes long sets and prepares them.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from setsim.functions.bitmap import BitmapSpec
from setsim.functions.spec import SimSpec
from setsim.functions.theory import resolve_cutoff
from setsim.operators import candidates as cand
from setsim.operators import cells as cell
from setsim.operators import shards as shard
from setsim.operators.block import block_candidates
from setsim.operators.components import connected_components
from setsim.operators.filters import suffix_ok
from setsim.operators.order import CODEC, HOT_DF, Collection, prepare, prepare_pair
from setsim.operators.verify import attach_tokens, finish, overlaps
from setsim.scratch import Scratch

METHODS = ("naive", "prefix_length", "prefix_positional", "prefix_suffix", "ell_prefix", "grouped_prefix", "block")
DEFAULT_BITMAP = BitmapSpec()
#: Members of classes whose ids (8 bytes each) are sent to every executor when pairs of classes are expanded.
SENT_MEMBERS = 1_000_000


def _bitmap(spec: SimSpec, bitmap: BitmapSpec | bool | None) -> tuple[BitmapSpec | None, int | None]:
    if bitmap is None or bitmap is False:
        return None, None
    resolved = (DEFAULT_BITMAP if bitmap is True else bitmap).resolved(spec)
    return resolved, resolve_cutoff(resolved, spec)


def candidates(method: str, left: Collection, right: Collection | None, spec: SimSpec, *, bitmap: BitmapSpec | bool | None = None, hbf_at: str = "auto", dedup: str = "auto", ell: int | str = 1, suffix_depth: int = 2, hbf_levels: str = "all", cap: int | None = None, kernel: str = "arrow", size_key: bool = False, hot_df: int = HOT_DF) -> DataFrame:
    """Unique candidate pairs of a method after its filters: ``sid_r, sid_s, n_r, n_s`` (and positions where it has them).

    ``size_key`` joins postings on token and size bucket; tokens of more than ``hot_df`` sets are joined in blocks.
    """
    own = right is None
    other = left if own else right
    spec_b, limit = _bitmap(spec, bitmap)
    sketched = lambda c, bits: c.sketch(bits) if bits else c.sets
    l_sets = sketched(left, spec_b)
    r_sets = l_sets if own else sketched(other, spec_b)
    common = {"self_join": own, "singles": left.singles}
    if method in METHODS[1:6]:
        common |= {"hot": left.hot(hot_df), "size_key": size_key}
    if dedup == "auto" and method in METHODS[1:4] + METHODS[5:6]:
        dedup = left.once(("dedup", spec), lambda: cand.choose_dedup(left.sets, spec))
    if method in ("prefix_length", "prefix_positional", "prefix_suffix"):
        at = hbf_at if hbf_at != "auto" else ("post" if dedup == "array" else "pre")
        found = cand.prefix_candidates(l_sets, r_sets, spec, **common, dedup=dedup, positional=method != "prefix_length", bitmap=spec_b, limit=limit, hbf_at=at)
        if method == "prefix_suffix":
            wide = attach_tokens(found, left.sets, other.sets)
            found = wide.filter(suffix_ok(spec, suffix_depth)).select(found.columns)
        return found
    if method == "ell_prefix":
        if ell == "adaptive":
            from setsim.plans.planner import choose_ell

            ell = left.once(("ell", spec), lambda: choose_ell(left, right, spec))
        return cand.ell_candidates(l_sets, r_sets, spec, int(ell), **common, bitmap=spec_b, limit=limit, hbf_levels=hbf_levels)
    if method == "grouped_prefix":
        return cand.group_candidates(l_sets, r_sets, spec, **common, dedup=dedup, bitmap=spec_b, limit=limit)
    if method == "block":
        if spec_b is None:
            spec_b = BitmapSpec("xor", 64, cutoff=None)
            l_sets = left.sketch(spec_b)
            r_sets = l_sets if own else other.sketch(spec_b)
        limit = None if spec_b.cutoff in (None, "auto") else limit  # this join tests every pair
        return block_candidates(l_sets, r_sets, spec, spec_b, self_join=own, limit=limit, cap=cap, how=kernel)
    raise ValueError(f"unknown method {method!r}: one of {METHODS}")


def naive(left: Collection, right: Collection | None, spec: SimSpec, form: str = "relational") -> DataFrame:
    """Baseline without filters. The relational form counts common tokens; the other compares all pairs of sets."""
    own = right is None
    other = left if own else right
    r = left.sets.select(F.col("sid").alias("sid_r"), F.col("n").alias("n_r"), F.col("toks").alias("toks_r"))
    s = other.sets.select(F.col("sid").alias("sid_s"), F.col("n").alias("n_s"), F.col("toks").alias("toks_s"))
    once = F.col("sid_s") < F.col("sid_r") if own else F.lit(True)
    if form == "nested_loop":
        pairs = r.join(s, once) if own else r.join(s, F.lit(True))
        counted = pairs.select("sid_r", "sid_s", "n_r", "n_s", F.size(F.array_intersect("toks_r", "toks_s")).alias("overlap"))
    else:
        a, b = r.select("sid_r", "n_r", F.explode("toks_r").alias("t")), s.select("sid_s", "n_s", F.explode("toks_s").alias("t"))
        pairs = a.join(b, "t").filter(once)
        counted = pairs.groupBy("sid_r", "sid_s").agg(F.min("n_r").alias("n_r"), F.min("n_s").alias("n_s"), F.count("*").cast("int").alias("overlap"))
    return finish(counted, spec, own)


#: Options of a token join that cells do not take: with one of them the join keeps to postings.
_TOKEN_ONLY = ("dedup", "hbf_at", "suffix_depth", "hbf_levels", "cap", "kernel")


def in_cells(collection: Collection, spec: SimSpec, method: str, *, bitmap: BitmapSpec | bool | None = None, ell: int | str = 1, cells: bool | str = "auto", **options) -> cell.Rule | None:
    """How a self-join's method runs in cells; None where postings write less, or an option asks for them."""
    if cells is False or method in ("naive", "grouped_prefix") or any(k in options for k in _TOKEN_ONLY):
        return None
    if ell == "adaptive" and method == "ell_prefix":
        return None
    every = method == "block"
    pays = lambda: cell.pays(collection.sets, spec, ell=int(ell), singles=collection.singles, all_pairs=every)
    if cells == "auto" and not collection.once(("cells", spec, ell, every), pays):
        return None
    bits, limit = _bitmap(spec, bitmap)
    if every:
        bits = bits or BitmapSpec("xor", 64, cutoff=None)
        limit = None if bits.cutoff in (None, "auto") else limit
    return cell.rule_of(method, spec, ell=int(ell), bitmap=bits, limit=limit)


def in_shards(collection: Collection, spec: SimSpec, method: str, *, bitmap: BitmapSpec | bool | None = None, ell: int | str = 1, cells: bool | str = "auto", shards: bool | str = "auto", **options) -> shard.Rule | None:
    """How a self-join's method runs in shards; None where it does not pay, or an option asks for postings or cells."""
    if shards is False or cells != "auto" or method not in shard.METHODS or ell == "adaptive" or any(k in options for k in (*_TOKEN_ONLY, "size_key", "hot_df")):
        return None
    bits, limit = _bitmap(spec, bitmap)
    rule = shard.rule_of(method, spec, ell=int(ell), bitmap=bits, limit=limit)
    return rule if shards is True or shard.pays(collection, rule) else None


def join_collections(left: Collection, right: Collection | None, spec: SimSpec, method: str = "prefix_length", *, verify: str = "intersect", universe: int | None = None, form: str = "relational", collapse: bool | str = "auto", cells: bool | str = "auto", shards: bool | str = "auto", **options) -> DataFrame:
    """Result pairs ``id_l, id_r, n_l, n_r, overlap, sim``; ``collapse`` joins one set per class of equal sets (self-joins).

    ``shards`` makes and verifies the candidates of a self-join of short sets at their tokens, ``cells`` those of others
    in pairs of blocks (see there), by default where that pays; a join in cells collapses by default where classes are at
    most half as many as sets.
    """
    if method == "naive":
        return naive(left, right, spec, form)
    if collapse is True and right is not None:
        raise ValueError("collapse works on self-joins")
    if right is None and verify == "intersect" and collapse is not True:
        at_tokens = in_shards(left, spec, method, cells=cells, shards=shards, **options)
        if at_tokens:
            return finish(shard.shard_join(left, at_tokens), spec, True)
    rule = in_cells(left, spec, method, cells=cells, **options) if right is None and verify == "intersect" and collapse is not True else None
    if collapse is True or (collapse == "auto" and rule and method != "block" and few_classes(left)):
        classes, members = left.once(("classes",), lambda: collapse_equal(left))
        found = join_collections(classes, None, spec, method, verify=verify, universe=universe, collapse=False, cells=cells, shards=shards, **options)
        return _expanded(found, classes, members, spec)
    if right is None and verify == "intersect":
        if rule:
            bits = options.get("bitmap") or (method == "block" and BitmapSpec("xor", 64, cutoff=None))
            bits = _bitmap(spec, bits)[0]
            return finish(cell.cell_join(left.cell_sets(bits), rule, singles=left.singles, kept=lambda make: left.once(cell.blocks_key(bits), make)), spec, True)
    found = candidates(method, left, right, spec, **options)
    other = left if right is None else right
    return finish(overlaps(found, left.sets, other.sets, spec, verify, universe), spec, right is None)


def similarity_join(left: DataFrame | Collection, right: DataFrame | Collection | None = None, *, measure: str = "jaccard", threshold="0.8", method: str = "prefix_length", bitmap: BitmapSpec | bool | None = None, **options) -> DataFrame:
    """Exact similarity join of long sets ``(sid, tok)`` or prepared collections; ``right=None`` is a self-join."""
    spec = SimSpec.of(measure, threshold)
    if not isinstance(left, Collection):
        if right is None:
            left = prepare(left)
        else:
            left, right = prepare_pair(left, right)
    return join_collections(left, right, spec, method, bitmap=bitmap, **options)


def few_classes(collection: Collection) -> bool:
    """Whether at most half as many sets are different as there are."""
    made = lambda: 2 * collection.sets.select(F.xxhash64("toks")).distinct().count() <= collection.sets.count()
    return collection.once(("few_classes",), made)


def collapse_equal(collection: Collection) -> tuple[Collection, DataFrame]:
    """One set per class of equal sets, and ``(sid, class_id)`` of all sets."""
    classes = collection.sets.groupBy("n", "toks").agg(F.min("sid").alias("class_id"))
    members = collection.sets.join(classes, ["n", "toks"]).select("sid", "class_id")
    sets = classes.select(F.col("class_id").alias("sid"), "n", "toks")
    scratch = Scratch(collection.spark, "classes") if collection.scratch else None
    if scratch:
        sets, members = scratch.save(sets, "sets"), scratch.save(members, "members")
    return Collection(sets, collection.vocab, 0, scratch), members


def _member_blocks(classes: Collection, members: DataFrame) -> DataFrame:
    """``(class_id, many, block, ids)``: the members of a class in ``many`` blocks by hash, some of which may be empty."""
    sized = members.join(members.groupBy("class_id").agg(F.count("*").alias("size")), "class_id")
    sized = sized.withColumn("many", F.ceil(F.col("size") / cand.GROUP_BLOCK).cast("int"))
    blocks = sized.groupBy("class_id", "many", F.pmod(F.xxhash64("sid"), "many").cast("int").alias("block")).agg(F.collect_list("sid").alias("ids"))
    return classes.scratch.save(blocks, "blocks", codec=CODEC) if classes.scratch else blocks


def _expanded(pairs: DataFrame, classes: Collection, members: DataFrame, spec: SimSpec) -> DataFrame:
    """Pairs of classes as pairs of their members, and the pairs within a class.

    Members of a class are dealt over blocks; a row of two blocks becomes pairs in generated code, so no pair is shuffled
    or joined. Blocks of up to ``SENT_MEMBERS`` members in all are sent to every executor.
    """
    blocks = classes.once(("member_blocks",), lambda: _member_blocks(classes, members))
    held = blocks.groupBy("class_id", "many").agg(F.sum(F.size("ids")).alias("size"))
    left, right = (held.select(F.col("class_id").alias(f"id_{x}"), F.col("many").alias(f"many_{x}")) for x in "lr")
    wide = pairs.join(left, "id_l").join(right, "id_r")
    own = held.filter("size > 1").join(classes.sets.select(F.col("sid").alias("class_id"), "n"), "class_id")
    own = own.select(*[F.col("class_id").alias(f"id_{x}") for x in "rl"], *[F.col("n").alias(x) for x in ("n_l", "n_r", "overlap")], *[F.col("many").alias(f"many_{x}") for x in "lr"])
    own = own.filter(spec.accepts_col("overlap", "n_l", "n_r")).withColumn("sim", spec.sim_col("overlap", "n_l", "n_r"))
    every = lambda side: F.explode(F.sequence(F.lit(0), F.col(f"many_{side}") - 1)).alias(f"block_{side}")
    columns = ["id_l", "id_r", "n_l", "n_r", "overlap", "sim"]
    tiles = wide.select(*columns, "many_r", every("l")).union(own.select(*columns, "many_r", every("l"))).select(*columns, "block_l", every("r"))
    # a number of tasks by bytes would be too small: a tile is a short row of up to GROUP_BLOCK ** 2 pairs
    spread = lambda df: df.repartition(4 * int(classes.spark.conf.get("spark.sql.shuffle.partitions")), "id_l", "id_r", "block_l", "block_r")
    tiles = spread(tiles.filter("id_l <> id_r OR block_l <= block_r"))
    small = members.count() <= SENT_MEMBERS
    for x in "lr":
        ids = blocks.select(F.col("class_id").alias(f"id_{x}"), F.col("block").alias(f"block_{x}"), F.col("ids").alias(f"ids_{x}"))
        tiles = tiles.join(F.broadcast(ids) if small else ids, [f"id_{x}", f"block_{x}"])
    if not small:  # by tiles again, as a class's block may meet many
        tiles = spread(tiles)
    alike = (F.col("id_l") == F.col("id_r")) & (F.col("block_l") == F.col("block_r"))
    each = tiles.select(*columns[2:], alike.alias("alike"), "ids_r", F.explode("ids_l").alias("one_l")).select(*columns[2:], "alike", "one_l", F.explode("ids_r").alias("one_r"))
    swap = F.col("one_r") < F.col("one_l")
    pick = lambda a, b: F.when(swap, F.col(a)).otherwise(F.col(b))
    each = each.filter(~F.col("alike") | (F.col("one_l") < F.col("one_r")))
    return each.select(pick("one_r", "one_l").alias("id_l"), pick("one_l", "one_r").alias("id_r"), pick("n_r", "n_l").alias("n_l"), pick("n_l", "n_r").alias("n_r"), "overlap", "sim")


# around the joins --------------------------------------------------------------------------------------------------------


def _ids(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.explode(F.array("id_l", "id_r")).alias("sid")).distinct()


def twins(sets: DataFrame, pairs: DataFrame) -> DataFrame:
    """Sets that have a similar partner."""
    return sets.join(_ids(pairs), "sid", "left_semi")


def without_twin(sets: DataFrame, pairs: DataFrame) -> DataFrame:
    """Sets that have none."""
    return sets.join(_ids(pairs), "sid", "left_anti")


def top_pairs(pairs: DataFrame, k: int) -> DataFrame:
    """The k most similar pairs, ties by ids."""
    return pairs.orderBy(F.desc("sim"), F.desc("overlap"), "id_l", "id_r").limit(k)


def top_partners(pairs: DataFrame, k: int) -> DataFrame:
    """The k best partners of every set that has any, with their place."""
    both = pairs.select(F.explode(F.array(F.struct(F.col("id_l").alias("id"), F.col("id_r").alias("partner")), F.struct(F.col("id_r").alias("id"), F.col("id_l").alias("partner")))).alias("x"), "overlap", "sim").select("x.*", "overlap", "sim")
    place = F.row_number().over(Window.partitionBy("id").orderBy(F.desc("sim"), "partner"))
    return both.withColumn("place", place).filter(F.col("place") <= k)


def components(pairs: DataFrame) -> DataFrame:
    """Clusters of similar sets: ``(node, component)``."""
    return connected_components(pairs, "id_l", "id_r")


def keep_one_per_cluster(sets: DataFrame, pairs: DataFrame) -> DataFrame:
    """The sets without those that have a partner of lower id in their cluster."""
    extra = components(pairs).filter("node <> component").select(F.col("node").alias("sid"))
    return sets.join(extra, "sid", "left_anti")
