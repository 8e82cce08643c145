"""Template classes of pages: order, nesting and roles against their definitions."""

from __future__ import annotations

import random
from collections import Counter
from itertools import combinations

import pytest

from rankjoin.llm import classes as cl
from rankjoin.llm import html


def _texts(spark, pages: list[str]) -> list[str]:
    rows = [(i, f"https://one.example/{i}", page) for i, page in enumerate(pages)]
    return [r.text for r in sorted(html.main_texts(spark.createDataFrame(rows, "page_id long, url string, html string")).collect(), key=lambda r: r.page_id)]


@pytest.mark.parametrize("most", [cl.BROADCAST_HOSTS, 0])
def test_occurrences_are_told_apart_by_the_classes_around_them(spark, monkeypatch, most):
    """One text, as often as nothing else: where it always stands before the heading it is template, behind it it is not."""
    monkeypatch.setattr(cl, "BROADCAST_HOSTS", most)
    page = "<html><body><div><p>Share</p></div><h1>title {}</h1><div>{}</div></body></html>"
    got = _texts(spark, [page.format(i, "<p>Share</p>" * (i % 3) + f"<p>story {i}</p>" * (1 + i % 4)) for i in range(8)])
    assert got == ["\n\n".join([f"title {i}", *["Share"] * (i % 3), *[f"story {i}"] * (1 + i % 4)]) for i in range(8)]


def test_texts_out_of_order_are_no_template(spark):
    """Texts of one occurrence vector whose order differs from page to page are not of one class."""
    page = "<html><body><article><h1>title {}</h1><p>{}</p><p>{}</p><p>story {}</p></article></body></html>"
    got = _texts(spark, [page.format(i, *(("one", "two") if i % 4 else ("two", "one")), i) for i in range(8)])
    assert got == [f"title {i}\n\ntwo\n\nstory {i}" for i in range(8)]


def _host(seed: int) -> list[list[int]]:
    """Pages of a host: blocks in varying numbers and order, some optional, with swaps and noise."""
    r = random.Random(seed)
    kinds = [cl.OPEN, cl.CLOSE, cl.TEXT, cl.ARTICLE]
    blocks = [[4 * r.randrange(1, 30) | r.choice(kinds) for _ in range(r.randrange(2, 6))] for _ in range(5)]
    frame = [4 * k | r.choice(kinds[:3]) for k in range(40, 46)]
    optional, loose, out = r.random(), r.random() / 3, []
    for _ in range(r.randrange(3, 9)):
        page: list[int] = []
        for k, token in enumerate(frame):
            page.append(token)
            if k < len(blocks) and r.random() < optional:
                page += blocks[k] * r.choice([1, 1, 2, 3])
            if r.random() < loose:
                page += r.choice(blocks)
        for _ in range(r.choice([0, 0, 1, 2])):
            i = r.randrange(len(page) - 1)
            page[i : i + 2] = page[i + 1], page[i]
        out.append(page)
    return out


def _occurrences(page: list[int], members: list[int]) -> list[list[int]]:
    """Positions of a class's roles on a page, occurrence by occurrence; fails if they do not keep the order."""
    at = [i for i, r in enumerate(page) if r in members]
    assert [page[i] for i in at] == members * (len(at) // len(members))
    return [at[i : i + len(members)] for i in range(0, len(at), len(members))]


def _inside(a: list[list[list[int]]], b: list[list[list[int]]]) -> bool:
    """Whether all occurrences of a, page by page, lie in one gap of b."""
    gaps = {next((k for o in outer for k in range(len(o) - 1) if o[k] < inner[0] and inner[-1] < o[k + 1]), -1) for xs, outer in zip(a, b) for inner in xs}
    return len(gaps) == 1 and -1 not in gaps


def test_classes_are_ordered_and_nested_until_nothing_changes(spark):
    hosts = {f"h{seed}": _host(seed) for seed in range(60)}
    rows = [(name, 1000 * h + i, page) for h, (name, pages) in enumerate(hosts.items()) for i, page in enumerate(pages)]
    pages = cl.written(spark.createDataFrame(rows, "host string, key long, roles array<long>"), "roles")
    found = {r.host: [(x["classes"], set(x["spare"])) for x in r.rounds] for r in cl.rounds(pages).collect()}
    many = nested = 0
    for name, at_first in hosts.items():
        seen = at_first
        for members, spare in found.get(name, [])[:-1]:
            seen = [cl.renamed(p, members, cl.places(members), spare)[0] for p in seen]
        final, spare = found.get(name, [([], set())])[-1]
        many, counts = max(many, len(found.get(name, []))), [Counter(p) for p in seen]
        assert len({r for m in final for r in m}) == sum(map(len, final))
        there = [[_occurrences(p, m) for p in seen] for m in final]
        for m in final:
            assert cl.weight(m) >= cl.CLASS
            assert all(len({c[r] for r in m}) == 1 for c in counts)
            assert sum(c[m[0]] > 0 for c in counts) >= (1 if any(r & 3 == cl.ARTICLE for r in m) else cl.SUPPORT) * len(seen)
        for a, b in combinations(there, 2):
            apart = all(x[-1] < y[0] or y[-1] < x[0] for xs, ys in zip(a, b) for x in xs for y in ys)
            nested += not apart
            assert apart or _inside(a, b) or _inside(b, a), name
        around: dict[int, set] = {}  # of every spare role, the gaps its occurrences stand in
        for k, p in enumerate(seen):
            for i, r in enumerate(p):
                if r in spare:
                    around.setdefault(r, set()).add(frozenset((c, j) for c, t in enumerate(there) for o in t[k] for j in range(len(o) - 1) if o[j] < i < o[j + 1]))
        assert all(len(x) == 1 for x in around.values()), name
    assert many > 2 and nested > 20
