"""URL filters, top-k, embedding near-dedup, shards, pipeline and registry."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from polyprov.llm.common import table

SF = "/root/testdata/sf0.001"


# ------------------------------------------------------------ url filters


def expected_rule(url, rules):
    if url is None or "://" not in url:
        return "", "", None, None
    import re

    rest = url.split("://", 1)[1]
    host = re.match(r"[^/?#]*", rest)[0]
    path = re.match(r"[^?#]*", rest[len(host) :])[0]
    host = "".join(c.lower() if "A" <= c <= "Z" else c for c in host)
    fits = [(r, v) for r, v in rules if (host == r.split("/", 1)[0] or host.endswith("." + r.split("/", 1)[0])) and path.startswith("/" + r.split("/", 1)[1])]
    rule = max(fits, key=lambda x: len(x[0]), default=(None, None))
    return host, path, *rule


URLS = [
    None, "", "no scheme", "http://", "https://A.Example.COM/en/7?x=1", "https://a.example.com/en/8", "https://com/en/1", "https://notcom/en/1", "https://x.net/de/8", "https://x.example.net/de/8/9#t",
    "https://x.net/de", "https://x.org/es/", "https://x.org?es/", "http://ÄB.org/es/1", "a://b.com/en/://c", "https://b.com/en/" + "y/" * 2000, "https://x.com//en/1", "https://x.com/en/1\n2",
]


def test_rules_equal_plain_python(spark):
    from polyprov.llm.url_filter import RULES, url_filter

    given = [r.url for r in table(spark, "/root/testdata/sf0.01", "pages").collect()]
    urls = URLS + given + URLS
    df = spark.createDataFrame([(i, u, "x", 1) for i, u in enumerate(urls)], "page_id long, url string, host string, labelled int")
    got = {r.page_id: r for r in url_filter(df).collect()}
    assert len(got) == len(urls)
    for i, u in enumerate(urls):
        host, path, rule, verdict = expected_rule(u, RULES)
        r = got[i]
        assert (r.host, r.path, r.rule) == (host, path, rule)
        assert r.verdict == verdict if rule else r.verdict in ("allow", "block")


def brute_tree(rows, kids_kept=8, least_rows=10, slack=0.1, least_labels=5, z=1.96, prior=0.1, strength=4.0, dilution=0.25, at=0.8):
    """rows: (id, host, path, verdict or None) -> {id: (template, verdict)}, by recursion over nodes."""
    import re
    from collections import Counter, defaultdict

    number = lambda s: re.fullmatch(r"[0-9]+([.][A-Za-z0-9]+)?", s)
    split = {i: [s for s in p.split("/") if s] for i, _, p, _ in rows}
    verdict = {i: v for i, _, _, v in rows}
    template = {}

    def labels(members):
        return sum(verdict[i] is not None for i in members), sum(verdict[i] == "block" for i in members)

    def content(members, level):
        below = [split[i][level:] for i in members]
        return Counter((re.sub("^[0-9]+", "*", b[0]) if b else "/", len(b)) for b in below)

    def same_content(one, two, level):
        h, g = content(one, level), content(two, level)
        apart = sum(abs(h[k] / len(one) - g[k] / len(two)) for k in h | g) / 2
        return apart <= (len(h | g) * (1 / len(one) + 1 / len(two))) ** 0.5 / 2 + slack

    def pools(kind):
        """Branches of one kind to pools."""
        known = sorted((k for k in kind if labels(k[1])[0] >= least_labels), key=lambda k: (labels(k[1])[1] / labels(k[1])[0], k[0]))
        out = []
        for k in known:
            n, bad = labels(k[1])
            if out:
                n0, bad0 = labels(out[-1][-1][1])
                pooled = (bad + bad0) / (n + n0)
                if bad / n - bad0 / n0 <= z * (pooled * (1 - pooled) * (1 / n + 1 / n0)) ** 0.5:
                    out[-1].append(k)
                    continue
            out.append([k])
        rest = [k for k in kind if k not in known]
        if len(out) == 1:
            return [out[0] + rest]
        return [*out, rest] if rest else out

    def grow(members, level, prefix):
        for i in members:
            if len(split[i]) == level:
                template[i] = prefix
        kids = defaultdict(list)
        for i in members:
            if len(split[i]) > level:
                kids[split[i][level]].append(i)
        n = sum(map(len, kids.values()))
        if len(kids) > kids_kept and len(kids) ** 2 > n:
            names = dict.fromkeys(kids, "*")
        else:
            names = {s: "*" if number(s) else s for s in kids}
            # Branches by what is most frequent below them; neighbours in that order are compared.
            some = [(s, m) for s, m in kids.items() if not number(s) and len(m) >= least_rows]
            main = {s: max(content(m, level + 1).items(), key=lambda kv: (kv[1], BIN[kv[0]])) for s, m in some}
            some.sort(key=lambda x: (BIN[main[x[0]][0]], main[x[0]][1] / len(x[1]), x[0]))
            chains = []
            for k, branch in enumerate(some):
                if k and same_content(some[k - 1][1], branch[1], level + 1):
                    chains[-1].append(branch)
                else:
                    chains.append([branch])
            for chain in chains:
                for pool in pools(chain):
                    if len(pool) > 1:
                        names |= {s: "{" + min(x for x, _ in pool) + "}" for s, _ in pool}
        nodes = defaultdict(list)
        for s, m in kids.items():
            nodes[names[s]] += m
        for name, m in nodes.items():
            grow(m, level + 1, f"{prefix}/{name}")

    hosts = defaultdict(list)
    for i, h, _, _ in rows:
        hosts[h].append(i)
    out = {}
    for members in hosts.values():
        grow(members, 0, "")
        leaves = defaultdict(list)
        for i in members:
            leaves[template[i]].append(i)
        for t, m in leaves.items():
            n, bad = labels(m)
            s = strength + dilution * (len(m) - n)
            judged = "block" if (bad + s * prior) / (n + s) >= at else "allow"
            out |= {i: (t, verdict[i] or judged) for i in m}
    return out


#: Bins of what may lie below a branch in the tests (set from Spark's hash).
BIN = {}


def test_tree_equals_brute_force(spark):
    from polyprov.llm.url_filter import BINS, RULES, url_filter

    rng = np.random.default_rng(2)
    urls = []
    for _ in range(2400):
        host = ["a.com", "b.com", "c.org", "d.net"][rng.integers(4)]
        urls.append(f"https://{host}/{['en', 'fr', 'shop', 'es'][rng.integers(4)]}/{['x', 'y', rng.integers(1000)][rng.integers(3)]}/{rng.integers(50)}/{'z/' * rng.integers(2)}")
    # Branches alike in content, one of them blocked; and one that differs in depth.
    urls += [f"http://e.net/{p}/{i}" for p in ("good", "bad1", "bad2", "bad3") for i in range(60 if p == "bad1" else 20)]
    urls += [f"http://f.com/{p}/{i}" for p, n in (("en", 200), ("de", 20)) for i in range(n)]
    urls += [f"http://e.net/deep/{i}/b/c/d/e/f.html" for i in range(30)] + ["http://e.net", "no url"]
    # A path that rules block in part: the rest of its template follows.
    rules = (*RULES, *((f"d.net/shop/x/{i}", "block") for i in (1, 2, 3, 4)), ("e.net/bad1/", "block"), ("e.net/good/", "allow"))
    rows = [(i, *(lambda h, p, r, v: (h, p, v))(*expected_rule(u, rules))) for i, u in enumerate(urls)]
    import re

    below = {(re.sub("^[0-9]+", "*", s[k]) if k < len(s) else "/", len(s) - k) for _, _, p, _ in rows for s in [[x for x in p.split("/") if x]] for k in range(1, len(s) + 1)}
    hashed = spark.createDataFrame(list(below), "kind string, depth int").withColumn("bin", F.pmod(F.xxhash64("kind", "depth"), F.lit(BINS))).collect()
    BIN.update({(r.kind, r.depth): r.bin for r in hashed})
    df = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    got = {r.page_id: (r.template, r.verdict) for r in url_filter(df, rules).collect()}
    assert got == brute_tree(rows)
    templates = {got[i][0] for i in got}
    assert "/deep/*/b/c/d/e/f.html" in templates and any("{" in t for t in templates)
    assert any(got[i][1] == "block" and rows[i][3] is None for i in got)


def test_unlabelled_branches_join_blocked_ones_on_pages(spark):
    """On pages shaped like the given ones: where a host's labels are nearly all bad, its other languages go."""
    from polyprov.llm.url_filter import url_filter

    urls = [f"https://blog.x.example.com/{lang}/{i}{'.html' if i % 3 else ''}" for lang, n in (("en", 400), ("de", 30), ("fr", 25)) for i in range(800, 800 + n)]
    urls += [f"https://www.y.example.org/{lang}/{i}" for lang, n in (("en", 300), ("es", 20)) for i in range(n)]
    out = {r.page_id: r for r in url_filter(spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")).collect()}
    first = lambda i: urls[i].split("/")[3]
    assert all(out[i].verdict == "block" and out[i].rule is None for i in range(455) if first(i) != "en")
    assert all(out[i].verdict == ("block" if first(i) == "es" else "allow") for i in range(455, len(urls)))


def test_url_filter_of_nothing_and_native(spark):
    from polyprov.llm.url_filter import url_filter

    df = spark.createDataFrame([], "page_id long, url string")
    out = url_filter(df)
    assert out.collect() == [] and "Python" not in out._jdf.queryExecution().executedPlan().toString()


# ------------------------------------------------------------ vectors

VECTORS = "vec_id long, embedding array<float>, label int, row string, v string"


def vectors(spark, rows):
    return spark.createDataFrame([(i, e, 0, "r", "v") for i, e in rows], VECTORS)


ODD = [None, [], [None, 1.0], [float("nan"), 1.0], [float("inf"), 1.0], [0.0, 0.0], [1.0, 0.0], [-1.0, 0.5], [1.0], [1.0, 0.0, 2.0]]


def brute_top(rows, k=10, every=100):
    x = {}
    for n, (i, e) in enumerate(rows):
        if i is not None and e is not None and all(c is not None and np.isfinite(c) for c in e):
            x[n] = (i, [int(np.floor(1024 * float(np.float32(c)))) for c in e])
    out = []
    for n, (i, e) in x.items():
        if i % every == 0:
            scores = sorted((-sum(a * b for a, b in zip(e, f, strict=False)), j) for m, (j, f) in x.items() if m != n)[:k]
            out += [(i, r + 1, j, -s) for r, (s, j) in enumerate(scores)]
    return sorted(out)


@pytest.mark.parametrize("shard_rows", [10**6, 15])
def test_top_k_equals_brute_force(spark, shard_rows):
    from polyprov.llm.topk import top_k

    rng = np.random.default_rng(0)
    rows = [(100 * i if i % 4 == 0 else i, [float(c) for c in rng.integers(-3, 4, 6)]) for i in range(120)] + [(1000 + n, e) for n, e in enumerate(ODD)] + [(0, [1.0] * 6), (0, [1.0] * 6), (None, [1.0] * 6)]
    got = sorted(tuple(r) for r in top_k(vectors(spark, rows), shard_rows=shard_rows).collect())
    assert got == brute_top(rows)


def test_top_k_of_large_values_and_nothing(spark):
    from polyprov.llm.topk import top_k

    rows = [(i, [1e12 * (i + 1), -1e11]) for i in range(12)] + [(100, [1e12, 1.0])]
    got = sorted(tuple(r) for r in top_k(vectors(spark, rows)).collect())
    want = sorted((a, b, c, min(max(s, -(2**63) + 2), 2**63 - 1)) for a, b, c, s in brute_top(rows))
    assert [g[:2] + g[3:] for g in got] == [w[:2] + w[3:] for w in want]
    assert top_k(vectors(spark, [])).collect() == [] and top_k(vectors(spark, [(1, [1.0])])).collect() == []


def test_ball_tree_bounds_hold():
    from polyprov.llm.topk import BallTree

    x = np.random.default_rng(3).normal(size=(700, 8))
    t = BallTree(x, 20)
    for node in range(len(t.radius)):
        a, b = t.span[node]
        d = np.sqrt(((x[t.order[a:b]] - t.centre[node]) ** 2).sum(axis=1))
        assert (d <= t.radius[node] + 1e-9).all()
    assert sorted(t.order) == list(range(700))


def brute_links(rows, least=0.95):
    live = [(n, i, np.array([np.float32(c) for c in e], np.float64)) for n, (i, e) in enumerate(rows) if i is not None and e and all(c is not None and np.isfinite(c) for c in e) and any(e)]
    links, parent = dict.fromkeys(range(len(rows)), 0), {i: i for i, _ in rows if i is not None}

    def find(a):
        while parent[a] != a:
            a = parent[a]
        return a

    for k, (n, i, x) in enumerate(live):
        for m, j, y in live[:k]:
            d = max(len(x), len(y))
            x1, y1 = np.pad(x, (0, d - len(x))), np.pad(y, (0, d - len(y)))
            if x1 @ y1 / (np.sqrt((x1 * x1).sum()) * np.sqrt((y1 * y1).sum())) >= least:
                links[n] += 1
                links[m] += 1
                a, b = find(i), find(j)
                if a != b:
                    parent[max(a, b)] = min(a, b)
    return sorted((str(i), links[n], find(i) if i is not None else None) for n, (i, _) in enumerate(rows))


def test_near_vectors_equal_brute_force(spark):
    from polyprov.llm.hnsw import near_vectors

    rng = np.random.default_rng(1)
    centre = rng.normal(size=8)
    rows = [(i, rng.normal(size=8).tolist()) for i in range(300)]
    rows += [(400 + i, (centre + rng.normal(size=8) * 0.05).tolist()) for i in range(120)]
    rows += [(600 + i, [1.0, 2.0] * 4) for i in range(30)] + [(900 + n, e) for n, e in enumerate(ODD)] + [(600, [1.0, 2.0] * 4), (None, [1.0, 2.0] * 4)]
    got = sorted((str(r.vec_id), r.n_links, r.component_id) for r in near_vectors(vectors(spark, rows), shard_rows=260).collect())
    assert got == brute_links(rows)
    assert near_vectors(vectors(spark, [])).collect() == []


def test_near_vectors_through_graphs_of_several_shards(spark):
    """Shards far above the size that is scanned whole; links within and between them."""
    from polyprov.llm.hnsw import near_vectors

    rng = np.random.default_rng(2)
    x = rng.normal(size=(4200, 32))
    for start, n, spread in ((0, 600, 0.05), (1000, 300, 0.12), (1500, 90, 0.05)):
        x[start : start + n] = x[start] + rng.normal(size=(n, 32)) * spread
    for i in range(2000, 2400, 2):
        x[i + 1] = x[i] + rng.normal(size=32) * 0.03
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    near = unit @ unit.T >= 0.95
    np.fill_diagonal(near, False)
    out = {r.vec_id: r for r in near_vectors(vectors(spark, [(i, v.tolist()) for i, v in enumerate(x)]), shard_rows=1400).collect()}
    links = np.array([out[i].n_links for i in range(len(x))])
    assert (links <= near.sum(axis=1)).all()
    linked = near.any(axis=1)
    assert (links[linked] / near.sum(axis=1)[linked]).mean() >= 0.98
    assert all(out[i].component_id == i for i in np.flatnonzero(~linked))
    assert sum(out[i].component_id == 0 for i in range(600)) >= 597
    assert sum(out[i + 1].component_id == i for i in range(2000, 2400, 2)) >= 196


def test_near_vectors_audit(spark):
    """The audit counts links to others only, over vectors that have some."""
    from polyprov.llm.hnsw import Graph, audited, link_answers, shares_found
    from polyprov.llm.vectors import packed

    rng = np.random.default_rng(5)
    x = rng.normal(size=(4000, 32))
    x[2000:3000] = x[0] + rng.normal(size=(1000, 32)) * 0.05
    x = (x / np.linalg.norm(x, axis=1, keepdims=True)).astype(np.float32)
    g, own = Graph(x), np.arange(1900, 2100)
    beam, margin, recall, n = audited(g, x[own], own, 0.95)
    true, got = shares_found(g, x[own], own, 0.95, beam, margin)
    exact = (x[own] @ x.T >= 0.95).sum(axis=1) - 1
    assert (true == exact).all() and n == (exact > 0).sum() and recall >= 0.99
    assert (got[true > 0] / true[true > 0]).mean() == pytest.approx(recall)
    v = packed(vectors(spark, [(i, r.tolist()) for i, r in enumerate(x[1000:3000].astype(float))])).withColumn("weight", F.lit(1).cast("long"))
    _, built = link_answers(v, 2000, 32, shard_rows=700)
    audits = built.collect()
    assert sum(r.n for r in audits) == 2000 and all(r.recall >= 0.99 and r.audited > 50 for r in audits)


def test_ties_unite_like_a_plain_search():
    from polyprov.llm.hnsw import Ties

    rng = np.random.default_rng(8)
    i, j = rng.integers(0, 400, 260), rng.integers(0, 400, 260)
    ties, plain = Ties(400), list(range(400))
    for k in range(0, 260, 37):
        ties.unite(i[k : k + 37], j[k : k + 37])
    for _ in range(400):
        for a, b in zip(i, j, strict=True):
            plain[a] = plain[b] = min(plain[a], plain[b])
    assert ties.label.tolist() == plain


# ------------------------------------------------------------ shards


def test_store_keeps_rows_and_versions(spark, tmp_path):
    from polyprov.llm.shards import Store, VersionTaken, compacted, placement

    docs = table(spark, SF, "documents")
    store = compacted(docs, f"file://{tmp_path}/store", target_bytes=60_000)
    assert store.read().exceptAll(docs).count() == 0 and store.read().count() == docs.count()
    out = placement(store, docs)
    assert out.count() == docs.count() and set(out.columns) >= {"doc_id", "shard", "version"}
    now = store.manifest()
    assert any(r.tier > 0 for r in now.runs)
    with pytest.raises(VersionTaken):
        store.commit(now)
    before = now.version
    store.append(docs.limit(3))
    assert store.manifest().version == before + 1 and store.read(before).count() == docs.count() and store.read().count() == docs.count() + 3


def test_store_edges(spark, tmp_path):
    from polyprov.llm.shards import Run, compacted, due, placement

    odd = spark.createDataFrame([(None, None, "a"), (1, "x", "b"), (1, "x", "b")], "doc_id long, text string, _arrival string")
    store = compacted(odd, f"file://{tmp_path}/odd")
    assert store.read().exceptAll(odd).count() == 0 and store.read().count() == 3 and placement(store, odd).count() == 3
    none = compacted(odd.limit(0), f"file://{tmp_path}/none")
    assert placement(none, odd).collect() == [] and none.read() is None
    runs = tuple(Run(i, ("f",), b, 0) for i, b in enumerate((100, 110, 90, 105, 1000, 5000)))
    assert sorted(r.id for r in due(runs, 4, 10**6)) == [0, 1, 2, 3] and due(runs, 5, 10**6) == () and due(runs, 4, 80) == ()


def test_store_writers_side_by_side(spark, tmp_path):
    """Appends that race commit one after the other; a merge of runs that are gone leaves nothing."""
    from concurrent.futures import ThreadPoolExecutor

    from polyprov.llm.shards import Store

    docs, folder = table(spark, SF, "documents"), f"file://{tmp_path}/race"
    with ThreadPoolExecutor(6) as pool:
        list(pool.map(lambda i: Store(spark, folder).append(docs.where(f"doc_id % 6 = {i}").coalesce(1)), range(6)))
    store = Store(spark, folder)
    assert store.manifest().version == 6 and store.read().exceptAll(docs).count() == 0 and store.read().count() == docs.count()
    runs = store.manifest().runs[:4]
    folders = [store._merge(runs) for _ in range(2)]
    store._added(folders[0], 1, runs)
    after = store.manifest()
    assert store._added(folders[1], 1, runs) == after and not store._files(folders[1])
    assert store.read().exceptAll(docs).count() == 0 and store.read().count() == docs.count()


def test_due_groups_are_disjoint_and_similar():
    from polyprov.llm.shards import Run, all_due

    rng = np.random.default_rng(4)
    for _ in range(50):
        runs = tuple(Run(i, ("f",), int(b), 0) for i, b in enumerate(rng.geometric(0.001, 40)))
        groups = all_due(runs, 4, 10**9)
        ids = [r.id for g in groups for r in g]
        assert len(ids) == len(set(ids)) and all(4 <= len(g) <= 8 for g in groups)
        assert all(max(r.bytes for r in g) <= 4 * min(r.bytes for r in g) for g in groups)


def test_store_of_long_texts(spark, tmp_path):
    from polyprov.llm.shards import compacted, placement

    d = spark.createDataFrame([(1, "long " * 400_000), (2, ""), (3, None)], "doc_id long, text string")
    out = {r.doc_id: r.n_bytes for r in placement(compacted(d, f"file://{tmp_path}/long"), d).collect()}
    assert out == {1: 2_000_000, 2: 0, 3: 0}


# ------------------------------------------------------------ pipeline and registry


def test_pipeline_stages(spark):
    import corpus_pipeline as cp

    docs = table(spark, SF, "documents")
    assert [n for n, _ in cp.STAGES] == ["quality classifier", "MinHash near-dedup", "mixing sources to target weights", "best-fit packing"]
    sizes = []
    for i, (_, stage) in enumerate(cp.STAGES):
        out = stage(spark, docs, SF)
        assert i == 3 or out.columns == docs.columns
        docs = out
        sizes.append(docs.count())
    assert 0 < sizes[1] <= sizes[0] < 200 and sizes[3] >= sizes[2] > 0
    assert cp.run(spark, SF).count() == sizes[3]


def test_pipeline_of_nothing(spark, tmp_path):
    import corpus_pipeline as cp

    docs = table(spark, SF, "documents").limit(0)
    for _, stage in cp.STAGES:
        docs = stage(spark, docs, SF)
        assert docs.count() == 0
    for name in ("documents", "labels"):
        table(spark, SF, name).limit(0).write.parquet(f"{tmp_path}/{name}.parquet")
    assert cp.run(spark, str(tmp_path)).count() == 0


def test_registry_names():
    from polyprov.llm import registry

    assert sorted(int(n[2:].split("_")[0]) for n in registry.queries() if n.startswith("op")) == list(range(1, 11))
    assert set(registry.oracle_sql()) <= set(registry.queries())


@pytest.mark.parametrize("name", ["op6_top_k", "op7_near_vectors", "op8_near_dup", "url_rules", "mix_targets"])
def test_queries_equal_their_sql(spark, name):
    import duckdb

    from polyprov.llm import registry

    duck = duckdb.connect()
    for t in ("documents", "embeddings", "pages"):
        duck.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    found = duck.execute(registry.oracle_sql()[name])
    columns = [c[0] for c in found.description]
    got = registry.queries()[name](spark, SF).select(columns).collect()
    assert sorted(map(tuple, got), key=str) == sorted(found.fetchall(), key=str)
