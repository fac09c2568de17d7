"""Codecs over a table of vectors, as one narrow pass plus windows over blocks; costs, measures and theory as tables.

Vectors are in whole grid units and draws are portable, so DuckDB gives the same rows from the same expressions.
"""

from __future__ import annotations

from math import inf

import numpy as np
import pyarrow as pa
from pyspark.sql import Window
from pyspark.sql import functions as F

from terse.functions.draws import draw, draw_sql
from terse.operators.codecs import Blocked, Codec, Identity, LargestK, LevelRounding, MultiLevel, NormTernary, RandomSparsify, SignScale
from terse.operators.relational import QUERIES as RELATIONAL
from terse.plans import costs, theory
from terse.sources.tables import read

QUERIES: dict = {}
WIRE = pa.schema([("vec_id", pa.int64()), ("coder", pa.string()), ("n_bytes", pa.int64()), ("same", pa.bool_())])
SQL: dict[str, str] = {}

#: the codecs of the queries, and for each the coded value of v as SQL (u: a draw; blk: the block of 16, or of unequal length; sums are of whole numbers, so exact)
UNEVEN = (10, 7, 47)
CODECS: dict[str, Codec] = {
    "codec_identity": Identity(),
    "codec_levels": LevelRounding((-1048576.0, 1048576.0)),
    "codec_level_grid": LevelRounding(tuple(float(x) for x in range(-1048576, 1048577, 131072))),
    "codec_random_sparsify": RandomSparsify(0.25),
    "codec_ternary_inf": NormTernary(inf, 16),
    "codec_ternary_2": NormTernary(2, 16),
    "codec_ternary_1": NormTernary(1, 16),
    "codec_ternary_whole": NormTernary(inf, None),
    "codec_blocked_uneven": Blocked(NormTernary(inf, None), UNEVEN),
    "codec_multilevel": MultiLevel(4),
    "codec_sign": SignScale(16),
    "codec_largest_k": LargestK(7),
}
W, WHOLE = "(PARTITION BY vec_id, rep, blk)", "(PARTITION BY vec_id, rep)"
TERNARY = "CASE WHEN u * ({s}) < abs(v) THEN sign(v) * ({s}) ELSE 0 END"
PLACE = f"(abs(v) / sqrt(sum(v * v) OVER {WHOLE}) * 4)"
EXPRESSIONS = {
    "codec_identity": "v",
    "codec_levels": "CASE WHEN u * 2097152 < v + 1048576 THEN 1048576 ELSE -1048576 END",
    "codec_level_grid": "floor(v / 131072) * 131072 + CASE WHEN u * 131072 < v - floor(v / 131072) * 131072 THEN 131072 ELSE 0 END",
    "codec_random_sparsify": "CASE WHEN u < 0.25 THEN v / 0.25 ELSE 0 END",
    "codec_ternary_inf": TERNARY.format(s=f"max(abs(v)) OVER {W}"),
    "codec_ternary_2": TERNARY.format(s=f"sqrt(sum(v * v) OVER {W})"),
    "codec_ternary_1": TERNARY.format(s=f"sum(abs(v)) OVER {W}"),
    "codec_ternary_whole": TERNARY.format(s=f"max(abs(v)) OVER {WHOLE}"),
    "codec_blocked_uneven": TERNARY.format(s=f"max(abs(v)) OVER {W}"),
    "codec_multilevel": f"sign(v) * sqrt(sum(v * v) OVER {WHOLE}) * ((floor({PLACE}) + CASE WHEN u < {PLACE} - floor({PLACE}) THEN 1 ELSE 0 END) / 4)",
    "codec_sign": f"sign(v) * (sum(abs(v)) OVER {W} / count(*) OVER {W})",
    "codec_largest_k": "CASE WHEN row_number() OVER (PARTITION BY vec_id, rep ORDER BY abs(v) DESC, coord) <= 7 THEN v ELSE 0 END",
}

COORDINATES = "SELECT vec_id, CAST(floor(CAST(unnest(embedding) AS DOUBLE) * 1048576 + 0.5) AS BIGINT) AS v, unnest(range(0, len(embedding))) AS coord FROM embeddings"
REPEATS = 4


def _block(name: str) -> str:
    return f"CASE WHEN coord < {UNEVEN[0]} THEN 0 WHEN coord < {UNEVEN[0] + UNEVEN[1]} THEN 1 ELSE 2 END" if name == "codec_blocked_uneven" else "CAST(floor(coord / 16) AS INT)"


def _coded(s, d, name, repeats=1):
    """(vec_id, rep, coord, blk, v, q): every element in grid units and its code, by the codec's array expression."""
    vals = F.transform("embedding", lambda e: F.floor(e.cast("double") * 1048576.0 + 0.5).cast("double"))
    base = read(s, d, "embeddings", "vec_id", "embedding").select("vec_id", vals.alias("vals"), F.explode(F.sequence(F.lit(0), F.lit(repeats - 1))).alias("rep"))
    q = CODECS[name].as_column(F.col("vals"), lambda i: draw(31, F.col("vec_id"), F.col("rep"), i, mode="portable"))
    long = base.withColumn("q", q).select("vec_id", "rep", F.posexplode(F.arrays_zip("vals", "q")).alias("coord", "x"))
    return long.select("vec_id", "rep", F.col("coord").cast("long").alias("coord"), F.expr(_block(name)).alias("blk"), F.col("x.vals").cast("long").alias("v"), F.col("x.q").cast("double").alias("q"))


def _coded_sql(name, repeats=1):
    reps = f"(SELECT unnest(range(0, {repeats})) AS rep)"
    drawn = f"SELECT vec_id, rep, coord, CAST(v AS DOUBLE) AS v, {draw_sql(31, 'vec_id', 'rep', 'coord')} AS u, {_block(name)} AS blk FROM ({COORDINATES}), {reps}"
    return f"SELECT vec_id, rep, coord, blk, v, CAST({EXPRESSIONS[name]} AS DOUBLE) AS q FROM ({drawn})"


_err = lambda: F.floor((F.col("q") - F.col("v")) * (F.col("q") - F.col("v")) + 0.5).cast("long")
ERR = "CAST(floor((q - v) * (q - v) + 0.5) AS BIGINT)"


def _codec(name):
    def build(s, d):
        return _coded(s, d, name).groupBy("vec_id", F.col("blk").cast("long").alias("block_id")).agg(
            F.floor(F.max(F.abs("q")) + 0.5).cast("long").alias("scale_grid"), F.count_if(F.col("q") != 0).alias("n_nonzero"), F.sum(_err()).alias("err2_grid")
        )

    QUERIES[name] = build
    SQL[name] = f"SELECT vec_id, CAST(blk AS BIGINT) AS block_id, CAST(floor(max(abs(q)) + 0.5) AS BIGINT) AS scale_grid, count(*) FILTER (q <> 0) AS n_nonzero, CAST(sum({ERR}) AS BIGINT) AS err2_grid FROM ({_coded_sql(name)}) GROUP BY vec_id, blk"


for _name in CODECS:
    _codec(_name)


def _add(name, sql, build):
    QUERIES[name] = build
    if sql:
        SQL[name] = sql


def _statistics(s, d):
    """By codec and vector: mean squared error over squared norm, and squared distance of the mean code from the vector, over repeats; sums of rounded codes are exact."""
    out = None
    for name in CODECS:
        rows = _coded(s, d, name, REPEATS).withColumn("n", F.floor(F.col("q") + 0.5).cast("long"))
        by = rows.groupBy("vec_id", "coord").agg(F.sum(_err()).alias("err2"), F.sum("n").alias("n"), F.first("v").alias("v"))
        off = F.col("n") - F.col("v") * REPEATS
        part = by.groupBy("vec_id").agg((F.sum("err2").cast("double") / (F.sum(F.col("v") * F.col("v")) * REPEATS)).alias("ratio"), F.sum(off * off).alias("bias2")).select(F.lit(name).alias("codec"), "vec_id", "ratio", "bias2")
        out = part if out is None else out.unionByName(part)
    return out


_add(
    "codec_variance_ratio",
    " UNION ALL ".join(
        f"SELECT '{n}' AS codec, vec_id, CAST(sum(err2) AS DOUBLE) / CAST(sum(v * v) * {REPEATS} AS DOUBLE) AS ratio, CAST(sum((n - v * {REPEATS}) * (n - v * {REPEATS})) AS BIGINT) AS bias2 FROM "
        f"(SELECT vec_id, coord, sum({ERR}) AS err2, CAST(sum(CAST(floor(q + 0.5) AS BIGINT)) AS BIGINT) AS n, CAST(any_value(v) AS BIGINT) AS v FROM ({_coded_sql(n, REPEATS)}) GROUP BY vec_id, coord) GROUP BY vec_id"
        for n in CODECS
    ),
    _statistics,
)


def _bias(s, d):
    """Sums of 16 codes of every element of every vector."""
    base = RELATIONAL["join_lateral"](s, d).withColumn("blk", F.expr("coord div 16"))
    scale = F.max(F.abs("v")).over(Window.partitionBy("vec_id", "blk"))
    rep = base.withColumn("scale", scale).withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(15))))
    hit = draw(32, F.col("vec_id"), F.col("coord"), F.col("rep"), mode="portable") * F.col("scale") < F.abs("v")
    return rep.groupBy("vec_id", "coord").agg(F.sum(F.when(hit, (F.signum("v") * F.col("scale")).cast("long")).otherwise(F.lit(0).cast("long"))).alias("total"), F.first("v").alias("v"))


_add(
    "codec_bias", f"SELECT vec_id, coord, CAST(sum(CASE WHEN {draw_sql(32, 'vec_id', 'coord', 'rep')} * scale < abs(v) THEN CAST(sign(v) * scale AS BIGINT) ELSE 0 END) AS BIGINT) AS total, min(v) AS v FROM (SELECT *, max(abs(v)) OVER (PARTITION BY vec_id, coord // 16) AS scale FROM ({COORDINATES})), (SELECT unnest(range(0, 16)) AS rep) GROUP BY vec_id, coord",
    _bias,
)


CODERS = ("PrefixTernary", "Base3", "GapCode", "SparsePairs")


def _vectors(s, d, name):
    """(vec_id, q): whole coded vectors."""
    rows = _coded(s, d, name).groupBy("vec_id").agg(F.sort_array(F.collect_list(F.struct("coord", "q"))).alias("c"))
    return rows.select("vec_id", F.transform("c", lambda e: e["q"]).alias("q"))


def _wire(s, d):
    """Packed bytes of every coded vector by four coders, and whether unpacking gives the vector back."""

    def run(batches):
        from terse.operators import wire

        for batch in batches:
            out = []
            for i, e in zip(batch.column("vec_id").to_pylist(), batch.column("q"), strict=True):
                q = e.values.to_numpy()
                for name in CODERS:
                    coder = getattr(wire, name)
                    pairs = coder is wire.SparsePairs
                    data = coder.pack(q) if pairs else wire.pack_ternary(q, 16, coder)
                    back = coder.unpack(data, len(q)) if pairs else wire.unpack_ternary(data, len(q), 16, coder)
                    out.append((i, name, len(data), bool(np.array_equal(back, q))))
            yield pa.RecordBatch.from_pylist([dict(zip(("vec_id", "coder", "n_bytes", "same"), r, strict=True)) for r in out], WIRE)

    return _vectors(s, d, "codec_ternary_inf").mapInArrow(run, "vec_id bigint, coder string, n_bytes bigint, same boolean")


_NZ = f"SELECT vec_id, coord, coord - coalesce(lag(coord) OVER (PARTITION BY vec_id ORDER BY coord), -1) AS gap FROM ({_coded_sql('codec_ternary_inf')}) WHERE q <> 0"
_SIZES = f"""SELECT vec_id, unnest(['PrefixTernary', 'Base3', 'GapCode', 'SparsePairs']) AS coder,
  unnest([16 + ceil((64 + n) / 8.0), 16 + 13, 16 + ceil((2 * floor(log2(n + 1)) + 1 + gap_bits) / 8.0), 4 + 4 * n + ceil(n * 6 / 8.0)]) AS n_bytes
FROM (SELECT e.vec_id, count(z.coord) AS n, coalesce(sum(2 * floor(log2(gap)) + 2), 0) AS gap_bits FROM embeddings e LEFT JOIN ({_NZ}) z ON e.vec_id = z.vec_id GROUP BY e.vec_id)"""
_add("codec_wire_roundtrip", f"SELECT vec_id, coder, CAST(n_bytes AS BIGINT) AS n_bytes, true AS same FROM ({_SIZES})", _wire)
_add(
    "bits_measured", f"SELECT coder, CAST(sum(n_bytes) AS BIGINT) AS n_bytes, CAST(sum(n_bytes) * 8 AS DOUBLE) / (count(*) * 64) AS bits_per_element FROM ({_SIZES}) GROUP BY coder",
    lambda s, d: _wire(s, d).groupBy("coder").agg(F.sum("n_bytes").alias("n_bytes"), ((F.sum("n_bytes") * 8).cast("double") / (F.count("*") * 64)).alias("bits_per_element")),
)


def _budget(s, d):
    """Expected elements kept of every vector (in millionths), and those kept for certain."""

    def run(batches):
        from terse.operators.codecs import BudgetSparsify

        for batch in batches:
            p = [BudgetSparsify(8).probabilities(e.values.to_numpy()) for e in batch.column("q")]
            sure = pa.array([int((x >= 1).sum()) for x in p], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column("vec_id"), pa.array([int(x.sum() * 1e6 + 0.5) for x in p], pa.int64()), sure], names=["vec_id", "expected", "certain"])

    return _vectors(s, d, "codec_identity").mapInArrow(run, "vec_id bigint, expected bigint, certain bigint")


_RANKED = f"SELECT vec_id, abs(v) AS m, row_number() OVER (PARTITION BY vec_id ORDER BY abs(v) DESC, coord) AS r, sum(abs(v)) OVER (PARTITION BY vec_id ORDER BY abs(v), coord DESC ROWS UNBOUNDED PRECEDING) AS rest FROM ({COORDINATES})"
_add(
    "codec_budget", f"SELECT vec_id, CAST(least(8, count(*) FILTER (m > 0)) * 1000000 AS BIGINT) AS expected, CAST(coalesce(min(r) FILTER (m * (9 - r) < rest OR r > 8), 9) - 1 AS BIGINT) AS certain FROM ({_RANKED}) GROUP BY vec_id", _budget,
)

# ---- costs ----------------------------------------------------------------------------------------------------------

SIZES = "SELECT d, block FROM (VALUES (64), (500), (11000000)) a(d), (VALUES (16), (64), (128), (256), (320), (512)) b(block)"
RAW, CODED = "(32.0::DOUBLE * d)", "(CAST(d AS DOUBLE) / block * 32.0::DOUBLE + d * 1.5::DOUBLE)"
VECTORS = "SELECT vec_id, CAST(len(embedding) AS BIGINT) AS d FROM embeddings WHERE len(embedding) > 0"
BLOCKED = f"SELECT vec_id, d, CAST(block AS BIGINT) AS block FROM ({VECTORS}), (VALUES {', '.join(f'({x})' for x in costs.BLOCKS)}) b(block)"
_blocked = lambda s, p: costs.blocked(costs.messages(s, p))
_add("bits_raw", f"SELECT vec_id, d, {RAW} AS bits FROM ({VECTORS})", lambda s, p: costs.messages(s, p).withColumn("bits", costs.bits_raw(F.col("d"))))
_add(
    "bits_ternary", f"SELECT vec_id, d, block, {CODED} AS bits, ceil(CAST(d AS DOUBLE) / block) * 32.0::DOUBLE + d * 1.5::DOUBLE AS exact FROM ({BLOCKED})",
    lambda s, p: _blocked(s, p).withColumns({"bits": costs.bits_ternary(F.col("d"), F.col("block")), "exact": costs.bits_ternary(F.col("d"), F.col("block"), exact=True)}),
)
_add("bits_rate", f"SELECT vec_id, d, block, {RAW} / {CODED} AS rate FROM ({BLOCKED})", lambda s, p: _blocked(s, p).withColumn("rate", costs.bits_raw(F.col("d")) / costs.bits_ternary(F.col("d"), F.col("block"))))
_legs = ", ".join(f"('{m}', {str(u).lower()}, {str(w).lower()})" for m, (u, w) in costs.LEGS.items())
_sent = f"CASE WHEN up THEN {CODED} ELSE {RAW} END + CASE WHEN down THEN {CODED} ELSE {RAW} END AS bits"
_per = f"SELECT method, CAST(d AS BIGINT) AS d, CAST(block AS BIGINT) AS block, {_sent} FROM ({SIZES}), (VALUES {_legs}) m(method, up, down)"
_per_vector = f"SELECT method, vec_id, d, block, {_sent} FROM ({BLOCKED}), (VALUES {_legs}) m(method, up, down)"
_add("bits_per_iteration", _per_vector, lambda s, p: costs.bits_per_iteration(s, _blocked(s, p)).drop("saving"))
_add("bits_saving", f"SELECT method, vec_id, d, block, 1 - bits / (2 * {RAW}) AS saving FROM ({_per_vector})", lambda s, p: costs.bits_per_iteration(s, _blocked(s, p)).drop("bits"))
_held = f"SELECT workers, count(DISTINCT (vec_id % workers + workers) % workers) AS n FROM ({VECTORS}), (VALUES (2), (5), (10), (20)) w(workers) GROUP BY workers"
_add(
    "bits_message_edges", f"SELECT topology, CAST(workers AS BIGINT) AS workers, CAST(CASE topology WHEN 'star' THEN 2 * n ELSE n * (n - 1) END AS BIGINT) AS messages FROM (VALUES ('star'), ('all_to_all')) t(topology), ({_held}) WHERE n > CASE topology WHEN 'star' THEN 0 ELSE 1 END",
    lambda s, p: costs.message_edges(s, p),
)
_add("bits_prefix_code", f"SELECT vec_id, CAST(sum(CASE WHEN q = 0 THEN 1 ELSE 2 END) AS BIGINT) AS bits FROM ({_coded_sql('codec_ternary_inf')}) GROUP BY vec_id", lambda s, d: _coded(s, d, "codec_ternary_inf").groupBy("vec_id").agg(F.sum(F.when(F.col("q") == 0, 1).otherwise(2)).alias("bits")))
_add("bits_sparse_pairs", f"SELECT vec_id, CAST(count(*) FILTER (q <> 0) * 38 AS BIGINT) AS bits FROM ({_coded_sql('codec_largest_k')}) GROUP BY vec_id", lambda s, d: _coded(s, d, "codec_largest_k").groupBy("vec_id").agg((F.count_if(F.col("q") != 0) * 38).alias("bits")))
_add(  # a given computing time, and coding at a given number of elements a second
    "time_vs_bandwidth",
    f"SELECT method, CAST(bw AS DOUBLE) AS bandwidth_mbps, {costs.COMPUTE_S!r}::DOUBLE + coded * d / {costs.CODING_RATE!r}::DOUBLE + 10 * (u + (bits - u)) / (bw * 1e6::DOUBLE) AS seconds FROM (SELECT method, d, bits, CASE method WHEN 'plain' THEN 0 WHEN 'two_sided_compensated' THEN 2 WHEN 'two_way_residual' THEN 2 ELSE 1 END AS coded, CASE WHEN method = 'plain' THEN {RAW} ELSE {CODED} END AS u FROM ({_per}) WHERE d = 11000000 AND block = 256), (VALUES (1000), (500), (200), (100), (50), (10)) l(bw)",
    lambda s, p: costs.time_vs_bandwidth(s),
)

# ---- theory ----------------------------------------------------------------------------------------------------------

CASES = ((7.5, 7.5, 20, 0.5, 5.0), (1.5, 1.5, 10, 1.0, 4.0), (1.5, 0.0, 10, 1.0, 4.0), (0.0, 0.0, 10, 1.0, 4.0))
_cases = f"(VALUES {', '.join(str(c) for c in CASES)}) v(c_up, c_down, n, mu, smooth)"
micro = lambda x: int(x * 1e6 + 0.5 // 1) if x >= 0 else -int(-x * 1e6 + 0.5)


def _theory(s, rows, ddl):
    return s.createDataFrame(rows, ddl)


def _recommended(s, d):
    rows = []
    for i, c in enumerate(CASES):
        r = theory.recommended(*c)
        rows.append((i, *[float(r[k]) for k in ("anchor_rate", "apply_rate", "extra", "step")]))
    raw = _theory(s, rows, "i int, anchor_rate double, apply_rate double, extra double, step double")
    return raw.select("i", *[F.floor(F.col(c) * 1e6 + 0.5).cast("long").alias(c) for c in raw.columns[1:]])


_i = "CAST(row_number() OVER () - 1 AS INT) AS i"
_m = lambda e: f"CAST(floor(CAST({e} AS DOUBLE) * 1e6 + 0.5) AS BIGINT)"
_add(
    "theory_recommended", f"SELECT {_i}, {_m('1 / (2 * (c_up + 1))')} AS anchor_rate, {_m('1 / (c_down + 1)')} AS apply_rate, {_m('4 * c_up * (c_up + 1) / n')} AS extra, {_m('2 / ((mu + smooth) * (1 + 2 * c_up / n))')} AS step FROM {_cases}",
    _recommended,
)
_add(
    "theory_factor", f"SELECT {_i}, {_m('greatest(2 * (c_up + 1), (c_down + 1) * (mu + smooth) * (mu + smooth) / (2 * mu * smooth) * (0.5 + c_up / n))')} AS ours, {_m('greatest(2 * (c_up + 1), (mu + smooth) / mu * (0.5 + c_up / n))')} AS difference FROM {_cases}",
    lambda s, d: _theory(s, [(i, theory.convergence_factor(*c), theory.gradient_difference_factor(c[0], *c[2:])) for i, c in enumerate(CASES)], "i int, a double, b double").select("i", F.floor(F.col("a") * 1e6 + 0.5).cast("long").alias("ours"), F.floor(F.col("b") * 1e6 + 0.5).cast("long").alias("difference")),
)
_half = "sqrt(greatest(0, 1 - 4 * 1.5 * 2.5 / (10 * e))) / 5"
_add(
    "theory_intervals", f"SELECT CAST(e AS DOUBLE) AS extra, {_m(f'0.2 - {_half}')} AS low, {_m(f'0.2 + {_half}')} AS high FROM (VALUES (1.5), (3.0), (6.0)) v(e)",
    lambda s, d: _theory(s, [(e, *map(float, theory.anchor_rate_interval(1.5, 10, e))) for e in (1.5, 3.0, 6.0)], "extra double, a double, b double").select("extra", F.floor(F.col("a") * 1e6 + 0.5).cast("long").alias("low"), F.floor(F.col("b") * 1e6 + 0.5).cast("long").alias("high")),
)
_add(
    "theory_contraction", f"SELECT CAST(c AS DOUBLE) AS carry, {_m('greatest(CASE WHEN c = 0 THEN 0 ELSE c * (1 + c) * 1.5 / 0.5 END, 1 + c * 0.2 - 2 * (1 + c) * 0.2 * 0.3 * 4 / 5, 0.8)')} AS rate FROM (VALUES (0.0), (0.05), (0.1)) v(c)",
    lambda s, d: _theory(s, [(c, float(theory.contraction(c, 0.2, 0.2, 0.3, 1.5, 1.0, 4.0))) for c in (0.0, 0.05, 0.1)], "carry double, r double").select("carry", F.floor(F.col("r") * 1e6 + 0.5).cast("long").alias("rate")),
)
_rates = ", ".join(f"('{m}', '{c}', '{a}', {str(li).lower()}, '{n}')" for m, c, a, li, n in theory.RATES)
_add("rates_table", f"SELECT * FROM (VALUES {_rates}) v(method, compresses, codec_assumption, linear, nonconvex)", lambda s, d: theory.rate_table(s))

# ---- Gram matrix ------------------------------------------------------------------------------------------------------


def _gram(s, d):
    """All pairs i <= j of coordinates, those that a vector holds: exact sums of its outer product by batch, then over batches."""
    import pandas as pd

    def run(frames):
        for f in frames:
            sizes = f.embedding.map(len).to_numpy()
            for n in np.unique(sizes[sizes > 0]):
                x = np.floor(np.stack(f.embedding[sizes == n]).astype(float) * 1048576 + 0.5).astype(np.int64)
                i, j = np.triu_indices(n)
                yield pd.DataFrame({"i": i, "j": j, "g": (x.T @ x)[i, j]})

    filled = read(s, d, "embeddings", "embedding").where("embedding is not null")
    return filled.mapInPandas(run, "i bigint, j bigint, g bigint").groupBy("i", "j").agg(F.sum("g").alias("g"))


_add("measure_gram", f"WITH c AS ({COORDINATES}) SELECT a.coord AS i, b.coord AS j, CAST(sum(a.v * b.v) AS BIGINT) AS g FROM c a JOIN c b ON a.vec_id = b.vec_id AND a.coord <= b.coord GROUP BY a.coord, b.coord", _gram)
