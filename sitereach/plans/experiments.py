"""The experiments: one parameter varies, the others keep their defaults, all methods are measured alike.

Every function returns plain rows (dicts) or a DataFrame of them; ``python -m sitereach.plans.experiments
SF_DIR NAME...`` prints them as JSON lines.
"""

from __future__ import annotations

import json
import sys
from collections.abc import Callable, Iterator
from time import perf_counter

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import City, parts_city
from ..operators import audience, influence, kvtree, policies, selection, workloads
from ..sources import keep

SOLVERS: dict[str, Callable[..., selection.Result]] = {
    "sampling_baseline": lambda c, cand, b, k, a: selection.sampling_baseline(c, cand, b, k, a, retrieval="batch"),
    "hybrid_approx": selection.hybrid_approx,
    "local_heuristic": selection.local_heuristic,
}


def common_influence(city: City, aud: DataFrame, sites: list[int], samples: int = 20_000, seed: int = 99) -> float:
    """Influence of chosen sites on samples that no method has seen."""
    users = city.users.select("usr").union(city.social.select("dst")).distinct()
    walks = influence.reverse_samples(city.social, aud, users, 1 << 50, samples, seed)
    return influence.coverage(walks, sites) * users.count() / samples


def measured(city: City, cand: DataFrame, b: int, k: int, alpha: float, methods: dict | None = None) -> Iterator[dict]:
    """The five panels of one setting: runtime and its selection share, influence, retrieval, selection and samples, certified ratio."""
    aud = keep(audience.batch(city, cand, k, alpha)[0], "audience")
    for name, solve in (methods or SOLVERS).items():
        began = perf_counter()
        r = solve(city, cand, b, k, alpha)
        total = perf_counter() - began
        yield {"method": name, "b": b, "k": k, "alpha": alpha, "total_s": round(total, 2), "selection_share": round(r.selection_s / total, 3), "retrieval_s": round(r.retrieval_s, 2), "selection_s": round(r.selection_s, 2), "samples": r.samples, "influence": round(common_influence(city, aud, r.sites), 2), "certified": r.certified, "sites": sorted(r.sites)}


def vary(city: City, what: str, values: list | None = None, n: int | None = None, methods: dict | None = None) -> Iterator[dict]:
    """b, k, alpha, n (candidates), users or sites (shares kept): one setting for each value."""
    d = workloads.DEFAULTS
    for value in values or workloads.GRID[{"users": "share", "sites": "share"}.get(what, what)]:
        size = value if what == "n" else n or d["n"]
        cand = keep(workloads.query_sets(city, size, 40).where("set_id = 1").select("poi"), "candidates")
        own = workloads.shared_users(city, value) if what == "users" else workloads.shared_sites(city, value, cand) if what == "sites" else city
        for row in measured(own, cand, value if what == "b" else d["b"], value if what == "k" else d["k"], value if what == "alpha" else d["alpha"], methods):
            yield {"varied": what, "value": value} | row


def effectiveness(city: City, b: int = 5, k: int = 20, alpha: float = 0.6, n: int = 60) -> Iterator[dict]:
    """Influence of the policies and of the certified choice on each query set."""
    sets = keep(workloads.query_sets(city, n, 40), "sets")
    for i in range(1, 5):
        cand = keep(sets.where(F.col("set_id") == i).select("poi"), "candidates")
        aud = keep(audience.batch(city, cand, k, alpha)[0], "audience")
        chosen = {
            "relevance": policies.most_relevant(city, cand, b), "influencer": policies.influencers(city, cand, b, k, alpha), "cardinality": policies.cardinality(aud, b),
            "random": policies.random_sites(cand, b), "rmss": selection.hybrid_approx(city, cand, b, k, alpha, retrieve=lambda a=aud: a).sites,
        }
        for name, sites in chosen.items():
            yield {"set_id": i, "policy": name, "influence": round(common_influence(city, aud, sites), 2), "sites": sorted(sites)}


def index_costs(city: City, k: int = 20) -> Iterator[dict]:
    """Build time and rows of the tree index and of the social matrix that the earlier index stores."""
    began = perf_counter()
    city, tree = kvtree.build(city, k)
    yield {"index": "keyword_voronoi_tree", "build_s": round(perf_counter() - began, 2), "rows": sum(x.count() for x in (tree.member, tree.border, tree.terms, tree.nearest))}
    began = perf_counter()
    rows = keep(audience.social_matrix(city), "matrix").count()
    yield {"index": "combined_bound_tree", "build_s": round(perf_counter() - began, 2), "rows": rows}


def pruning(city: City, k: int = 20, alpha: float = 0.6, n: int = 60) -> Iterator[dict]:
    """Bound computations and unpruned users of each pruning mode."""
    cand = keep(workloads.drawn_sites(city, n), "candidates")
    city, tree = kvtree.build(city, k)
    for mode in audience.PRUNE_MODES:
        yield {"mode": mode} | audience.candidates_of(city, cand, k, alpha, tree, mode)[1]


def estimator_bias(city: City, k: int = 10, alpha: float = 0.6, n: int = 20, samples: int = 20_000) -> Iterator[dict]:
    """Hybrid estimates with the exclusive and the inclusive remote part, over plain estimates of the same set."""
    cand = keep(workloads.drawn_sites(city, n), "candidates")
    aud = keep(audience.batch(city, cand, k, alpha)[0], "audience")
    users = city.users.select("usr").union(city.social.select("dst")).distinct()
    walks, size = keep(influence.reverse_samples(city.social, aud, users, 0, samples), "walks"), users.count()
    pois = [r["poi"] for r in cand.collect()]
    for b in (1, 3, 5, 9):
        sites = policies.cardinality(aud, b) or pois[:b]
        plain = influence.coverage(walks, sites) * size / samples
        local = selection.local_influence(city.social, aud, [sites])[0]
        yield {"b": b, "plain": round(plain, 3)} | {m: round(influence.hybrid_estimate(local, influence.coverage(walks, sites, m), size, samples) / plain, 4) if plain else None for m in ("exclusive", "inclusive")}


EXPERIMENTS = {f"vary_{x}": (lambda c, x=x: vary(c, x)) for x in ("b", "n", "k", "alpha", "users", "sites")} | {"effectiveness": effectiveness, "index_costs": index_costs, "pruning": pruning, "estimator_bias": estimator_bias}


def run(spark: SparkSession, sf_dir: str, names: list[str]) -> Iterator[dict]:
    city = parts_city(spark, sf_dir).kept(keep)
    for name in names or EXPERIMENTS:
        for row in EXPERIMENTS[name](city):
            yield {"experiment": name} | row


if __name__ == "__main__":
    session = SparkSession.builder.master("local[*]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    session.sparkContext.setLogLevel("ERROR")
    for out in run(session, sys.argv[1], sys.argv[2:]):
        print(json.dumps(out), flush=True)
