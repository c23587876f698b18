import numpy as np
import pytest

from linkrank.llm import vectors as vec
from tests.llm.oracle import same
from tests.llm.test_components import brute as components


def brute(rows):
    """(n_links, component) of each row by comparing all pairs."""
    ok = [e is not None and l is not None and i is not None and all(v is not None and np.isfinite(v) for v in e) and any(e) for i, e, l in rows]
    links = [(x, y) for x in range(len(rows)) for y in range(x) if ok[x] and ok[y] and rows[x][2] == rows[y][2] and len(rows[x][1]) == len(rows[y][1])
             and np.dot(rows[x][1], rows[y][1]) / np.linalg.norm(rows[x][1]) / np.linalg.norm(rows[y][1]) >= vec.COSINE]
    root = components(links)
    least = {}
    for x in root:
        least[root[x]] = min(least.get(root[x], 1 << 60), rows[x][0])
    return [(sum(x in p for p in links), least[root[x]] if x in root else rows[x][0]) for x in range(len(rows))]


def made(n, groups, seed=0, spread=0.1):
    rng = np.random.default_rng(seed)
    centre = rng.standard_normal((groups, 16))
    out = []
    for k in range(n):
        g = int(rng.integers(groups))
        v = centre[g] + spread * rng.standard_normal(16) if k % 3 else rng.standard_normal(16)
        out.append((k, [float(np.float32(x)) for x in v], g % 3))
    return out


@pytest.mark.parametrize("block", [256, 8])
def test_equals_brute_force(spark, monkeypatch, block):
    monkeypatch.setattr(vec, "BLOCK", block)
    rows = made(500, 9) + [(600 + k, [1.0] * 16, 1) for k in range(40)] + [(700, [3.0] * 16, 1), (701, [1.0] * 16, 2)]
    got = {r.vec_id: (r.n_links, r.component_id) for r in vec.near_copies(spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").repartition(6)).collect()}
    want = dict(zip((r[0] for r in rows), brute(rows)))
    assert got == want and sum(n for n, _ in want.values()) > 1000


@pytest.mark.parametrize("worth", [1000, 1])
def test_recall_of_groups_of_near_copies(spark, monkeypatch, worth):
    """All links of a label whose vectors lie in groups of one to hundreds of near copies."""
    monkeypatch.setattr(vec, "WORTH", worth)
    rng = np.random.default_rng(12)
    rows = []
    for size in [1] * 1500 + [2] * 200 + [5] * 60 + [40] * 8 + [300]:
        centre = rng.standard_normal(64)
        rows += [centre + (0.08 if size > 1 else 0) * rng.standard_normal(64) for _ in range(size)]
    x = np.array(rows, np.float32).astype(float)
    df = spark.createDataFrame([(k, v, 1) for k, v in enumerate(x.tolist())], "vec_id long, embedding array<float>, label int")
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    want = (x @ x.T >= vec.COSINE).sum(1) - 1
    got = {r.vec_id: r.n_links for r in vec.near_copies(df).collect()}
    assert want.sum() > 1000 and sum(got[k] == n for k, n in enumerate(want)) >= 0.999 * len(want)


def test_edges(spark):
    rows = [(1, None, 1, 0), (2, [0.0, 0.0], 1, 0), (3, [1.0, None], 1, 0), (4, [float("nan"), 1.0], 1, 0), (5, [float("inf"), 1.0], 1, 0), (6, [1.0, 2.0], None, 0), (None, [1.0, 2.0], 1, 0),
            (7, [1.0, 2.0], 1, 0), (7, [1.0, 2.0], 1, 0), (8, [2.0, 4.0], 1, 0), (9, [1.0, 2.0, 0.0], 1, 0), (10, [1.0, 2.0], 2, 0), (11, [], 1, 0), (12, [-0.0, 1.0], 3, 0), (13, [0.0, 1.0], 3, 0)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int, n_links int")
    got = sorted(((r.vec_id or 0, r.n_links, r.component_id, r.kept) for r in vec.near_copies(df).collect()), key=str)
    alone = [(k, 0, k, True) for k in (1, 2, 3, 4, 5, 6, 9, 10, 11)]
    assert got == sorted([*alone, (0, 0, None, True), (7, 2, 7, True), (7, 2, 7, True), (8, 2, 7, False), (12, 1, 12, True), (13, 1, 12, False)], key=str)
    assert vec.near_copies(df.limit(0)).count() == 0


def test_equals_sql(spark):
    same(spark, vec.query, vec.ORACLE, "/root/testdata/sf0.01")


def dense(n, background, pairs, seed=3):
    """Vectors of one label with a cosine of about ``background`` to each other, and near copies of the first ones."""
    rng = np.random.default_rng(seed)
    x = np.sqrt(background) * np.eye(1, 64) + np.sqrt((1 - background) / 64) * rng.standard_normal((n, 64))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    aside = rng.standard_normal((pairs, 64))
    aside -= (aside * x[:pairs]).sum(1, keepdims=True) * x[:pairs]
    y = 0.982 * x[:pairs] + np.sqrt(1 - 0.982**2) * aside / np.linalg.norm(aside, axis=1, keepdims=True)
    return np.concatenate([x, y]).astype(np.float32)


@pytest.mark.parametrize("worth, least", [(1000, 1.0), (10, 0.985)])
def test_dense_label(spark, monkeypatch, worth, least):
    """Near copies in a crowded label are found: by all pairs, and, where those would cost more, by more passes."""
    monkeypatch.setattr(vec, "WORTH", worth)
    x = dense(8000, 0.93, 300)
    got = {r.vec_id: r.n_links for r in vec.near_copies(spark.createDataFrame([(k, v, 1) for k, v in enumerate(x.tolist())], "vec_id long, embedding array<float>, label int")).collect()}
    unit = x.astype(float) / np.linalg.norm(x.astype(float), axis=1, keepdims=True)
    want = (unit @ unit.T >= vec.COSINE).sum(1) - 1
    near = np.flatnonzero(want)
    assert len(near) >= 600 and len(got) == 8300 and all(got[k] <= want[k] for k in got)
    assert sum(got[k] == want[k] for k in near) >= least * len(near)


@pytest.mark.parametrize("worth", [1000, 1])
def test_no_link_is_lost_at_any_size(spark, monkeypatch, worth):
    """Labels that were compared whole up to WORTH x 20 vectors, and beyond by passes that ended with some links unseen."""
    monkeypatch.setattr(vec, "WORTH", worth)
    x = dense(6000, 0.93, 3000)
    got = {r.vec_id: r.n_links for r in vec.near_copies(spark.createDataFrame([(k, v, 1) for k, v in enumerate(x.tolist())], "vec_id long, embedding array<float>, label int")).collect()}
    unit = x.astype(float) / np.linalg.norm(x.astype(float), axis=1, keepdims=True)
    want = (unit @ unit.T >= vec.COSINE).sum(1) - 1
    assert want.sum() >= 6000 and [got[k] for k in range(len(x))] == want.tolist()


def test_runs_far_apart_are_left_out(spark, monkeypatch):
    """Two crowds on opposite sides: no run of one is compared with one of the other."""
    rng = np.random.default_rng(6)
    side = np.repeat([1.0, -1.0], 600)[:, None] * np.eye(1, 16)
    x = side + 0.02 * rng.standard_normal((1200, 16))
    monkeypatch.setattr(vec, "WORTH", 1)
    monkeypatch.setattr(vec, "BLOCK", 200)
    moved = []
    monkeypatch.setattr(vec, "_may_link", lambda cosine, f=vec._may_link: moved.append(f(cosine)) or f(cosine))
    df = spark.createDataFrame([(k, v, 1) for k, v in enumerate(x.tolist())], "vec_id long, embedding array<double>, label int")
    got = {r.vec_id: r.n_links for r in vec.near_copies(df).collect()}
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    assert [got[k] for k in range(1200)] == ((unit @ unit.T >= vec.COSINE).sum(1) - 1).tolist() and moved
    far, near = unit[:600].mean(0), unit[600:].mean(0)
    import pyarrow as pa

    columns = [pa.array(["x"] * 2), pa.array([16] * 2), pa.array([0, 0]), pa.array([0, 1]), pa.array([far.tobytes()] * 2), pa.array([0.2, 0.2]), pa.array([far.tobytes(), near.tobytes()]), pa.array([0.2, 0.2])]
    batch = pa.record_batch(columns, names=["label", "size", "a", "b", "ca", "ra", "cb", "rb"])
    assert next(moved[0]([batch])).column("b").to_pylist() == [0]
