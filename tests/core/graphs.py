"""Micro graphs with known ranks (damping 0.85, uniform start, no term for dangling vertices)."""

from linkrank.graph import Graph

EDGES = {
    "chain3": [(0, 1), (1, 2)],
    "cycle4": [(0, 1), (1, 2), (2, 3), (3, 0)],
    "complete4": [(a, b) for a in range(4) for b in range(4) if a != b],
    "star_in5": [(k, 0) for k in range(1, 5)],
    "star_both5": [(k, 0) for k in range(1, 5)] + [(0, k) for k in range(1, 5)],
    "twins5": [(0, 2), (0, 3), (1, 2), (1, 3), (2, 4), (3, 4), (4, 0)],
}
RANKS = {
    "chain3": [0.05, 0.0925, 0.128625],
    "cycle4": [0.25] * 4,
    "complete4": [0.25] * 4,
    "star_in5": [0.132] + [0.03] * 4,
    "star_both5": [0.132 / (1 - 0.7225)] + [0.03 + 0.85 / 4 * 0.132 / (1 - 0.7225)] * 4,
    "twins5": [0.30391642, 0.03, 0.17191448, 0.17191448, 0.32225462],
}


def graph(spark, name_or_edges, **options):
    edges = EDGES[name_or_edges] if isinstance(name_or_edges, str) else name_or_edges
    return Graph.from_edges(spark.createDataFrame(edges, "src long, dst long"), **options)


def ranks(result):
    frame = getattr(result, "ranks", result)
    return {r.id: r.rank for r in frame.collect()}


def close(got, want, within=1e-8):
    want = dict(enumerate(want)) if isinstance(want, list) else want
    return got.keys() == want.keys() and all(abs(got[k] - want[k]) <= within for k in want)


def random_edges(rng, n, m):
    return list({(a, b) for a, b in ((rng.randrange(n), rng.randrange(n)) for _ in range(m)) if a != b})
