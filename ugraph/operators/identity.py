"""Identity uncertainty: components of reference sets, their legal worlds and the marginals of entities."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.tables import materialise, ship

SET_OFFSET = 1_000_000_000
#: References of a component up to which all its worlds are listed; beyond, this many are drawn.
MOST_REFS, DRAWS = 20, 4096
#: Entities of a component: a world is a mask of 63 bits.
MOST_ENTITIES = 63
#: Entities of a world up to which marginals of all its subsets are tabled; others are taken from the worlds on demand.
MOST_TABLED = 14


def balanced_prior(p: Column, m: Column) -> Column:
    """The singleton prior with which an isolated set of m references exists with its stated probability p."""
    return F.pow(F.pow(p, m - 1) * (1 - p), F.lit(1.0) / m)


def complete_singletons(sets: DataFrame, refs: DataFrame, prior: str = "balanced") -> DataFrame:
    """``sets`` (set_id, members, p) with a singleton for each reference that has none: ref_id, p, is_single.

    A reference of several sets takes the geometric mean of their balanced priors, one of none takes 1; ``one`` takes 1
    and ``complement`` the product of the complements throughout."""
    rows = sets.filter("size(members) > 1").select(F.explode("members").alias("ref_id"), "p", F.size("members").alias("m"))
    q = {
        "balanced": F.exp(F.avg(F.log(F.greatest(balanced_prior(F.col("p"), F.col("m")), F.lit(1e-6))))),
        "one": F.max(F.lit(1.0)),
        "complement": F.greatest(F.product(1 - F.col("p")), F.lit(1e-6)),
    }[prior]
    own = sets.filter("size(members) = 1").select(F.col("members")[0].alias("ref_id"), F.col("p").alias("given"))
    out = refs.select("ref_id").distinct().join(rows.groupBy("ref_id").agg(q.alias("q")), "ref_id", "left").join(own, "ref_id", "left")
    return out.select("ref_id", F.coalesce("given", "q", F.lit(1.0)).alias("p"))


def identity_components(sets: DataFrame, most_rounds: int = 50) -> DataFrame:
    """ref_id, comp_id (least reference reachable over shared sets) of the references of multi-member sets, by
    least-label propagation with a jump over the label found."""
    member = materialise(sets.filter("size(members) > 1").select("set_id", F.explode("members").alias("ref_id")), "members")
    label = materialise(member.select("ref_id").distinct().withColumn("comp_id", F.col("ref_id")), "comps")
    total = None
    for _ in range(most_rounds):
        now = label.agg(F.sum("comp_id"), F.count(F.lit(1))).first()
        if now == total:
            return label
        total = now
        per_set = member.join(label, "ref_id").groupBy("set_id").agg(F.min("comp_id").alias("low"))
        near = member.join(per_set, "set_id").groupBy("ref_id").agg(F.min("low").alias("low"))
        jump = label.select(F.col("ref_id").alias("low"), F.col("comp_id").alias("far"))
        label = materialise(near.join(jump, "low", "left").select("ref_id", F.least("low", F.coalesce("far", "low")).alias("comp_id")), "comps")
    raise RuntimeError("components did not settle")


def exact_covers(refs: list[int], sets: list[tuple[int, frozenset]]) -> list[tuple[int, ...]]:
    """All ways to cover every reference exactly once, as tuples of entity ids."""
    of = {r: [s for s in sets if r in s[1]] for r in refs}
    out: list[tuple[int, ...]] = []

    def go(open_: frozenset, taken: tuple[int, ...]) -> None:
        if not open_:
            out.append(tuple(sorted(taken)))
            return
        r = min(open_, key=lambda x: (len(of[x]), x))
        for e, members in of[r]:
            if members <= open_:
                go(open_ - members, (*taken, e))

    go(frozenset(refs), ())
    return out


WORLDS = "comp_id long, mask long, p double"


def _by_component(one):
    """Batches of (comp_id, xs) to the rows (comp_id, mask, p) that ``one`` makes of each."""

    def run(batches):
        kinds = (("comp_id", pa.int64()), ("mask", pa.int64()), ("p", pa.float64()))
        for part in (b.slice(i, 64) for b in batches for i in range(0, b.num_rows, 64)):
            rows = [r for x in part.to_pylist() for r in one(x["comp_id"], x["xs"])]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, (_, t) in enumerate(kinds)], names=[n for n, _ in kinds])

    return run


def _worlds(weighting: str, most: int, draws: int, seed: int):
    def one(comp: int, ents: list[dict]) -> list[tuple[int, int, float]]:
        ents = sorted((x["entity_id"], frozenset(x["refs"]), x["p"], x["bit"]) for x in ents)
        refs = sorted({r for _, m, _, _ in ents for r in m})
        if len(ents) > MOST_ENTITIES:
            raise ValueError(f"component {comp} has {len(ents)} entities; worlds hold {MOST_ENTITIES} at most: drop its least probable sets")
        info = {e: (p ** (len(m) if weighting == "per_reference" else 1), 1 << b) for e, m, p, b in ents}
        if len(refs) > most:
            return list(_sampled(comp, refs, ents, info, draws, seed)[["comp_id", "mask", "p"]].itertuples(index=False, name=None))
        rows = []
        for cover in exact_covers(refs, [(e, m) for e, m, _, _ in ents]):
            w, mask = 1.0, 0
            for e in cover:
                w *= info[e][0]
                mask |= info[e][1]
            rows.append((comp, mask, w))
        z = sum(w for _, _, w in rows)
        if z <= 0:
            raise ValueError(f"component {comp} has no legal world")
        return [(c, m, w / z) for c, m, w in rows if w > 0]

    return _by_component(one)


def _sampled(comp, refs, ents, info, draws, seed):
    """Worlds by importance sampling: references are covered in order, each by a set drawn by its weight. v is a world's
    part in the variance of a marginal's estimate."""
    rng = np.random.default_rng((seed, comp % (1 << 32)))
    found: dict[int, float] = {}
    square: dict[int, float] = {}
    for _ in range(draws):
        open_, mask, ratio = set(refs), 0, 1.0
        while open_:
            r = min(open_)
            fit = [(e, m) for e, m, _, _ in ents if r in m and m <= open_]
            w = np.array([info[e][0] for e, _ in fit])
            if not fit or w.sum() <= 0:
                ratio = 0.0
                break
            e, m = fit[int(rng.choice(len(fit), p=w / w.sum()))]
            ratio *= w.sum()
            mask |= info[e][1]
            open_ -= m
        if ratio:
            found[mask] = found.get(mask, 0.0) + ratio
            square[mask] = square.get(mask, 0.0) + ratio * ratio
    z = sum(found.values())
    if z <= 0:
        raise ValueError(f"component {comp}: no legal world in {draws} draws")
    return pd.DataFrame([(comp, m, w / z, square[m] / z / z) for m, w in sorted(found.items())], columns=["comp_id", "mask", "p", "v"])


def component_worlds(entities: DataFrame, weighting: str = "per_reference", most_refs: int = MOST_REFS, draws: int = DRAWS, seed: int = 7) -> DataFrame:
    """comp_id, mask, p of all legal worlds: entities (comp_id, entity_id, refs, p, bit) that cover each reference
    once. Components of more than ``most_refs`` references get ``draws`` drawn worlds instead."""
    rows = entities.filter("comp_id is not null").select("comp_id", "entity_id", "refs", "p", "bit")
    ship(entities.sparkSession)
    packed = rows.groupBy("comp_id").agg(F.collect_list(F.struct("entity_id", "refs", "p", "bit")).alias("xs"))
    return packed.mapInArrow(_worlds(weighting, most_refs, draws, seed), WORLDS)


def sampled_marginals(entities: DataFrame, draws: int = DRAWS, weighting: str = "per_reference", seed: int = 7) -> DataFrame:
    """comp_id, entity_id, p, se: the probability that an entity exists, from drawn worlds, and its standard error."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        ents = sorted((int(e), frozenset(int(x) for x in m), float(p), int(b)) for e, m, p, b in zip(pdf.entity_id, pdf.refs, pdf.p, pdf.bit, strict=True))
        info = {e: (p ** (len(m) if weighting == "per_reference" else 1), 1 << b) for e, m, p, b in ents}
        comp = int(pdf.comp_id.iloc[0])
        worlds = _sampled(comp, sorted({r for _, m, _, _ in ents for r in m}), ents, info, draws, seed)
        rows = []
        for e, _, _, b in ents:
            has = (worlds["mask"].to_numpy() >> b) & 1 == 1
            p = float(worlds.p[has].sum())
            rows.append((comp, e, p, float(np.sqrt((worlds.v * np.where(has, 1 - p, p) ** 2).sum()))))
        return pd.DataFrame(rows, columns=["comp_id", "entity_id", "p", "se"])

    rows = entities.filter("comp_id is not null").select("comp_id", "entity_id", "refs", "p", "bit")
    ship(entities.sparkSession)
    return rows.groupBy("comp_id").applyInPandas(run, "comp_id long, entity_id long, p double, se double")


def _subsets(comp: int, worlds: list[dict]) -> list[tuple[int, int, float]]:
    total: dict[int, float] = {}
    for w in worlds:
        mask = sub = w["mask"]
        if mask.bit_count() > MOST_TABLED:
            raise ValueError(f"component {comp}: worlds of over {MOST_TABLED} entities have no table of marginals; take them on demand")
        while sub:
            total[sub] = total.get(sub, 0.0) + w["p"]
            sub = (sub - 1) & mask
    return [(comp, m, p) for m, p in sorted(total.items())]


def component_marginals(worlds: DataFrame) -> DataFrame:
    """comp_id, mask, p: the probability that all entities of the mask exist together, for every possible mask. Components
    with a world of over MOST_TABLED entities are left out: they have too many masks, and ``marginal_on_demand`` serves them."""
    ship(worlds.sparkSession)
    packed = worlds.groupBy("comp_id").agg(F.collect_list(F.struct("mask", "p")).alias("xs"), F.max(F.bit_count("mask")).alias("n"))
    return packed.filter(F.col("n") <= MOST_TABLED).select("comp_id", "xs").mapInArrow(_by_component(_subsets), WORLDS)


def marginal_on_demand(worlds: Column, mask: Column) -> Column:
    """The same from an array of a component's worlds, without a table of all masks."""
    return F.aggregate(F.filter(worlds, lambda w: w["mask"].bitwiseAND(mask) == mask), F.lit(0.0), lambda a, w: a + w["p"])


def existence_probability(entities: DataFrame, wanted: DataFrame) -> DataFrame:
    """``wanted`` (set_key, entity_id) to set_key, p: the probability that a set's entities exist together; components
    multiply. 0 where one of them is no entity."""
    rows = wanted.distinct().join(entities.select("entity_id", "comp_id", "mask", "worlds"), "entity_id", "left")
    known = F.col("mask").isNotNull()
    per = rows.groupBy("set_key", "comp_id").agg(F.bit_or("mask").alias("mask"), F.first("worlds").alias("worlds"), F.min(known).alias("known"))
    p = F.when(~F.col("known"), 0.0).when(F.col("comp_id").isNull(), 1.0).otherwise(marginal_on_demand(F.col("worlds"), F.col("mask")))
    return per.groupBy("set_key").agg(F.product(p).alias("p"))


def pn_expr(names: list[str]) -> Column:
    """Probability that the nodes exist together. Node x has columns c_x (component or null), m_x (its bit) and w_x
    (its component's worlds). Components multiply; inside one, the joint marginal is taken."""
    out = F.lit(1.0)
    for i, x in enumerate(names):
        c = F.col(f"c_{x}")
        mask = F.col(f"m_{x}")
        for y in names[:i] + names[i + 1 :]:
            mask = mask.bitwiseOR(F.when(F.col(f"c_{y}") == c, F.col(f"m_{y}")).otherwise(F.lit(0)))
        before = F.lit(False)
        for y in names[:i]:
            before = before | F.coalesce(F.col(f"c_{y}") == c, F.lit(False))
        out = out * F.when(c.isNull() | before, F.lit(1.0)).otherwise(marginal_on_demand(F.col(f"w_{x}"), mask))
    return out
