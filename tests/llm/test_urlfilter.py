from __future__ import annotations

import hashlib
import math
import random
from collections import Counter

from kgfeat.llm import urlfilter as uf


def brute_parts(u):
    u = u or ""
    if "://" not in u:
        return "", ""
    rest = u.split("://", 1)[1]
    cut = min([rest.find(c) for c in "/?#" if c in rest], default=len(rest))
    host = "".join(c.lower() if "A" <= c <= "Z" else c for c in rest[:cut])
    path = rest[cut:]
    path = path[: min([path.find(c) for c in "?#" if c in path], default=len(path))]
    return host, path


def brute_rule(host, path):
    fit = [(len(h + p), h + p, v) for v, h, p in uf.RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
    return max(fit)[1:] if fit else (None, None)


class Brute:
    def __init__(self, good, bad, order):
        self.n = [Counter(), Counter()]
        self.order = order
        for side, urls in enumerate((good, bad)):
            for u in urls:
                p = uf.PAD * order + u + uf.STOP
                for i in range(order, len(p)):
                    for k in range(order + 1):
                        self.n[side][p[i - k : i + 1]] += 1
        self.alphabet = 1 + len({g for n in self.n for g in n if len(g) == 1})

    def p(self, side, ctx, c):
        q = 1 / self.alphabet
        for k in range(self.order + 1):
            x = ctx[len(ctx) - k :]
            after = {g[-1]: v for g, v in self.n[side].items() if len(g) == k + 1 and g[:k] == x}
            t, d = sum(after.values()), len(after)
            if t:
                q = (after.get(c, 0) + d * q) / (t + d)
        return q

    def score(self, u):
        p, s = uf.PAD * self.order + u + uf.STOP, 0
        for i in range(self.order, len(p)):
            s += round(1e6 * (math.log(self.p(0, p[i - self.order : i], p[i])) - math.log(self.p(1, p[i - self.order : i], p[i]))))
        return math.floor(s / (len(u) + 1))


URLS = [None, "", "nohost", "http://", "HTTP://WWW.Example.ORG", "x://a.example.org/es/1?q#f", "x://example.org/en/12", "x://example.org/en/2", "x://badexample.org/es/", "x://é.com/fr/", "x://a.com/de/x", "x://a.com/dex", "x://org?x", "x://org/", "x://a.net/en/1://b", "x://a.net\n/p\nq?r"]


def test_parts_and_rules(spark):
    got = uf.judge(spark, spark.createDataFrame(list(enumerate(URLS)) + [(3, URLS[3])], "page_id long, url string"))
    rows = {r["id"]: r for r in got.collect()}
    assert got.count() == len(URLS) + 1
    for i, u in enumerate(URLS):
        host, path = brute_parts(u)
        rule, verdict = brute_rule(host, path)
        assert (rows[i]["host"], rows[i]["path"], rows[i]["rule"]) == (host, path, rule), u
        assert verdict is None or rows[i]["verdict"] == verdict


def _corpus():
    rng = random.Random(6)
    w = lambda cs: "".join(rng.choice(cs) for _ in range(6))
    out = [f"http://{w('abcde')}.example.org/docs/{w('abcde')}" for _ in range(60)] + [f"http://{w('xyz')}.com/de/{w('xyz123')}" for _ in range(60)]
    return out + [f"http://{w('abcde')}.net/docs/{w('abcde')}" for _ in range(20)] + [f"http://{w('xyz')}.net/de/{w('xyz123')}" for _ in range(20)] + [None, "", out[0], out[0]]


def test_scores_against_brute_force(spark):
    urls = _corpus()
    df = spark.createDataFrame([(i, u, 0) for i, u in enumerate(urls)], "page_id long, url string, host int")
    got = {r["id"]: r for r in uf.judge(spark, df, order=3).collect()}
    given = [brute_rule(*brute_parts(u))[1] for u in urls]
    held = [int(hashlib.md5((u or "").encode()).hexdigest()[:8], 16) % 5 == 0 for u in urls]
    b = Brute([u or "" for u, g, h in zip(urls, given, held, strict=True) if g == "allow" and not h], [u or "" for u, g, h in zip(urls, given, held, strict=True) if g == "block" and not h], 3)
    for i, (u, g) in enumerate(zip(urls, given, strict=True)):
        if g is None:
            assert abs(got[i]["score"] * 1e6 - b.score(u or "")) <= 2
    free = range(120, 160)
    right = sum(got[i]["verdict"] == ("allow" if i < 140 else "block") for i in free)
    assert right >= 38


def test_empty_table(spark):
    assert uf.judge(spark, spark.createDataFrame([], "page_id long, url string")).count() == 0


def test_calibration_picks_the_gap(spark):
    df = spark.createDataFrame([(True, x * 10_000) for x in (5, 6, 9)] + [(False, x * 10_000) for x in (-4, -1, 2)], "y boolean, s long")
    assert uf.calibrate(df) == 30_000
    apart = spark.createDataFrame([(True, 90_000), (False, -90_000)], "y boolean, s long")
    assert uf.calibrate(apart) == 0
