"""Template deduction: ordered, nested equivalence classes of page tokens, host by host, until nothing changes.

A page is a sequence of roles, one per token occurrence. A role starts as the token's hash; its two lowest bits say what it is
(OPEN, CLOSE, TEXT, or ARTICLE for a text that must be on all pages). A round

1. puts the host's frequent roles with one occurrence vector into a class (`_sums`),
2. tests order: the k-th occurrences of a class's roles must stand in one order on all pages, before any (k+1)-th. A class that fails
   is split: each page puts roles that keep to the order into groups (`split`), and roles with one group on every page stay together,
3. tests nesting: all occurrences of a class must lie in one gap of another, or none inside it (`nesting`). Of two classes that fail,
   the one with fewer occurrences gives way: cut at the gaps where the other lies if it is the outer one, else dissolved (`resolved`),
4. tells occurrences of all other frequent roles apart by the gaps of classes around them (`renamed`).

Hosts whose roles the last step split go through another round. Roles are only ever split, so this ends. Vectors, groups and gaps
are compared by sums of hashes that each task adds up for its pages; no task gathers a host's pages.
"""

from __future__ import annotations

from bisect import bisect
from collections import defaultdict
from collections.abc import Iterable, Iterator
from functools import reduce

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankjoin.llm.common import few, free_name, join_uneven, releasing, written

OPEN, CLOSE, TEXT, ARTICLE = range(4)
PAGES, CLASS, SUPPORT = 3, 2, 0.5
BROADCAST_HOSTS, BROADCAST_ROLES = 20_000, 2_000_000
MASK = 0xFFFFFFFFFFFFFFFF


def signed(h: int) -> int:
    return h - (1 << 64) if h >> 63 else h


def _hash(seed: int, *numbers: int) -> int:
    return xxhash.xxh64_intdigest(b"".join((n & MASK).to_bytes(8, "little") for n in numbers), seed & MASK)


def weight(members: Iterable[int]) -> int:
    """Roles of a class; an element counts once, by its start."""
    return sum(r & 3 != CLOSE for r in members)


def places(classes: list[list[int]]) -> dict[int, tuple[int, int]]:
    """Class and rank of every role."""
    return {r: (c, k) for c, members in enumerate(classes) for k, r in enumerate(members)}


def split(at: list[list[int]], order: list[int]) -> list[int]:
    """The leader of each rank's group on a page: at holds the positions of each rank, order says which rank joins first.

    A rank joins the first group in which it keeps to the order: behind the rank before it, ahead of the next, occurrence by occurrence.
    """
    groups: list[tuple[int, list[int]]] = []
    leader = [0] * len(at)
    for r in order:
        for first, group in groups:
            i = bisect(group, r)
            before = at[group[i - 1]] if i else at[group[-1]][:-1]
            after = at[group[i]] if i < len(group) else at[group[0]][1:]
            if all(a < b for a, b in zip(before, at[r] if i else at[r][1:])) and all(a < b for a, b in zip(at[r], after)):
                group.insert(i, r)
                leader[r] = first
                break
        else:
            groups.append((r, [r]))
            leader[r] = r
    return leader


def out_of_order(roles: list[int], classes: list[list[int]], known: dict[int, tuple[int, int]], old: set[int]) -> Iterator[tuple[int, int]]:
    """Roles of a page that are not in their class's main group, with the leader of their group."""
    seen: dict[int, list[tuple[int, int]]] = defaultdict(list)
    for i, r in enumerate(roles):
        if r in known:
            c, k = known[r]
            seen[c].append((k, i))
    for c, met in seen.items():
        members = classes[c]
        n = len(members)
        if all(k == j % n for j, (k, _) in enumerate(met)):
            continue
        at: list[list[int]] = [[] for _ in members]
        for k, i in met:
            at[k].append(i)
        order = sorted(range(n), key=lambda k: (members[k] not in old, k))
        for k, first in enumerate(split(at, order)):
            if first != order[0]:
                yield members[k], members[first]


def walk(roles: list[int], classes: list[list[int]], known: dict[int, tuple[int, int]]) -> Iterator[tuple[int, int, int, list[list[int]]]]:
    """(index, class, rank, open classes with their last rank), outermost first, at every occurrence; class -1 is none."""
    open_: list[list[int]] = []
    for i, r in enumerate(roles):
        c, k = known.get(r, (-1, 0))
        yield i, c, k, open_
        if c >= 0:
            if k == 0:
                open_.append([c, 0])
            else:
                for entry in reversed(open_):
                    if entry[0] == c:
                        entry[1] = k
                        break
            if k == len(classes[c]) - 1:
                for j in range(len(open_) - 1, -1, -1):
                    if open_[j][0] == c:
                        del open_[j]
                        break


def nesting(roles: list[int], classes: list[list[int]], known: dict[int, tuple[int, int]]) -> dict[tuple[int, int, int], int]:
    """How many occurrences of a class begin in a gap of another: (inner, outer, gap); (inner, inner, 0) counts all. Gap -1: they cross."""
    out: dict[tuple[int, int, int], int] = defaultdict(int)
    for _, c, k, open_ in walk(roles, classes, known):
        if c < 0:
            continue
        if k == 0:
            out[c, c, 0] += 1
            for outer, gap in open_:
                out[c, outer, gap] += 1
        else:
            for other, _ in reversed(open_):
                if other == c:
                    break
                out[other, c, -1] += 1
    return out


def resolved(classes: list[list[int]], pages: list[int], met: dict[tuple[int, int, int], int]) -> list[list[int]]:
    """Classes that are nested with one another: those with most occurrences first, others cut or dissolved to suit them."""
    gaps: dict[tuple[int, int], dict[int, int]] = defaultdict(dict)
    partners: dict[int, set[int]] = defaultdict(set)
    for (inner, outer, gap), n in met.items():
        if inner != outer:
            gaps[inner, outer][gap] = n
            partners[inner].add(outer)
            partners[outer].add(inner)
    cuts: dict[int, set[int]] = {}  # of classes that stay

    def nested(inner: int, outer: int) -> bool:
        found = gaps.get((inner, outer), {})
        return not found or (len(found) == 1 and sum(found.values()) == met[inner, inner, 0])

    for c in sorted(range(len(classes)), key=lambda c: (-pages[c] * len(classes[c]), classes[c])):
        cut: set[int] = set()
        for other in partners[c]:
            if other not in cuts:
                continue
            inside, around = gaps.get((c, other), {}), gaps.get((other, c), {})
            if -1 in inside or -1 in around or (not nested(c, other) and not cuts[other].issuperset(inside)):
                break
            if not nested(other, c):
                cut.update(around)
        else:
            cuts[c] = cut
    out = []
    for c, cut in cuts.items():
        ends = [0, *(g + 1 for g in sorted(cut)), len(classes[c])]
        out += [part for a, b in zip(ends, ends[1:]) if weight(part := classes[c][a:b]) >= CLASS]
    return out


def renamed(roles: list[int], classes: list[list[int]], known: dict[int, tuple[int, int]], spare: set[int]) -> tuple[list[int], list[int]]:
    """Roles after a round and where they stood: those of classes stay, spare ones take the gaps around them into their hash, all others go."""
    out, at = [], []
    for i, c, _, open_ in walk(roles, classes, known):
        r = roles[i]
        if c < 0:
            if r not in spare:
                continue
            if open_:
                r = signed(_hash(r, *(n for outer, gap in open_ for n in (classes[outer][0], gap)))) & ~3 | r & 3
        out.append(r)
        at.append(i)
    return out, at


def prepared(found: list[tuple[list[list[int]], list[int]]]) -> tuple[list[tuple], set[int]]:
    """A host's rounds (classes and spare roles) for `template`: all but the last to go through, and the roles of the last one's classes."""
    return [_state(*r) for r in found[:-1]], {r for members, _ in found[-1:] for m in members for r in m}


def template(roles: list[int], steps: list[tuple], final: set[int]) -> set[int]:
    """Where roles of the template stand on a page."""
    if not final:
        return set()
    at = list(range(len(roles)))
    for step in steps:
        roles, kept = renamed(roles, *step)
        at = [at[i] for i in kept]
    return {i for i, r in zip(at, roles, strict=True) if r in final}


def lists(column: pa.ListArray) -> Iterator[list[int]]:
    """The lists of a column of numbers."""
    ends, values = column.offsets.to_pylist(), column.values.to_numpy(zero_copy_only=False)
    return (values[a:b].tolist() for a, b in zip(ends, ends[1:]))


def with_host(pages: DataFrame, hosts: DataFrame, how: str = "inner") -> DataFrame:
    """pages with the row of hosts for their host (n: pages, roles: size of its arrays); a host's pages are never gathered."""
    many, size = hosts.agg(F.count("*"), F.sum("roles")).first()
    hosts = hosts.drop("roles")
    if many <= BROADCAST_HOSTS and (size or 0) <= BROADCAST_ROLES:
        return pages.join(F.broadcast(hosts), "host", how)
    if how == "inner":
        (mark,) = free_name(pages, "_there")
        return join_uneven(pages, hosts.withColumn(mark, F.lit(1)), "host", "n").where(F.col(mark).isNotNull()).drop(mark)
    return join_uneven(pages, hosts, "host", "n")


def _summed(pages: DataFrame, schema: str, by: list[str], each, *given: str) -> DataFrame:
    """Sums over pages (host, key, roles; given: columns of the host) of what each(state, host, key, roles, sums) adds: `by` is the key."""
    names = [c.split()[0] for c in schema.split(", ")]

    @releasing
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sums: dict[tuple, list[int]] = {}
            states: dict[str, tuple] = {}
            for i, (name, key, roles) in enumerate(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), lists(batch.column(2)), strict=True)):
                if name not in states:
                    states[name] = _state(*(batch.column(3 + j)[i].as_py() for j in range(len(given))))
                each(states[name], name, key, roles, sums)
            rows = [[*k, *v] for k, v in sums.items()]
            yield pa.RecordBatch.from_arrays([pa.array([r[j] for r in rows], pa.string() if j == 0 else pa.int64()) for j in range(len(names))], names=names)

    out = pages.select("host", "key", "roles", *given).mapInArrow(work, schema)
    return out.groupBy(*by).agg(*(F.sum(c).alias(c) for c in names if c not in by))


def _state(classes: list[list[int]] | None = None, others: list[int] | None = None) -> tuple:
    return classes or [], places(classes or []), set(others or ())


def _add(sums: dict, key: tuple, *numbers: int) -> None:
    s = sums.setdefault(key, [0] * len(numbers))
    for j, n in enumerate(numbers):
        s[j] += n


def _vectors(_, name: str, key: int, roles: list[int], sums: dict) -> None:
    often: dict[int, list[int]] = {}
    for i, r in enumerate(roles):
        if r in often:
            often[r][0] += 1
        else:
            often[r] = [1, i]
    hashes: dict[int, int] = {}
    for r, (n, first) in often.items():
        h = hashes.get(n)
        if h is None:
            h = hashes[n] = _hash(key, n)
        _add(sums, (name, r), h & 0xFFFFFFFF, h >> 32, 1, first)


def _groups(state, name: str, key: int, roles: list[int], sums: dict) -> None:
    for r, leader in out_of_order(roles, *state):
        h = _hash(key, leader)
        _add(sums, (name, r), h & 0xFFFFFFFF, h >> 32)


def _nested(state, name: str, key: int, roles: list[int], sums: dict) -> None:
    for (inner, outer, gap), n in nesting(roles, state[0], state[1]).items():
        _add(sums, (name, inner, outer, gap), n)


def _by_host(vectors: DataFrame, *by: str) -> DataFrame:
    """host, classes, pages (of each class), old (roles that were in classes), roles: large enough classes of roles that agree in the columns by."""
    members, size = F.sort_array(F.collect_list(F.struct("first", "role", "old"))), F.sum((F.col("role").bitwiseAND(F.lit(3)) != CLOSE).cast("int"))
    groups = vectors.groupBy("host", *by).agg(members.alias("m"), size.alias("w"), F.max("pages").alias("pages")).where(f"w >= {CLASS}")
    return groups.groupBy("host").agg(F.sort_array(F.collect_list(F.struct("m", "pages"))).alias("c")).select(
        "host", F.expr("transform(c, x -> x.m.role)").alias("classes"), F.expr("transform(c, x -> x.pages)").alias("pages"),
        F.expr("flatten(transform(c, x -> transform(filter(x.m, y -> y.old), y -> y.role)))").alias("old"), F.expr("aggregate(c, 0L, (s, x) -> s + size(x.m))").alias("roles"),
    )


def _round(pages: DataFrame, often: DataFrame, of: DataFrame) -> DataFrame:
    """host, n, classes, spare, roles of a round over pages (host, key, roles) with their frequent roles and which of these were in classes."""
    same = written(_by_host(often, "x", "y").join(of, "host"), "classes")
    wrong = _summed(with_host(pages, same.drop("pages")), "host string, role long, gx long, gy long", ["host", "role"], _groups, "classes", "old")
    ordered = written(_by_host(often.join(wrong, ["host", "role"], "left").na.fill(0, ["gx", "gy"]), "x", "y", "gx", "gy").join(of, "host"), "ordered")
    met = _summed(with_host(pages, ordered.drop("pages", "old")), "host string, inner long, outer long, gap long, n long", ["host", "inner", "outer", "gap"], _nested, "classes")
    met = met.groupBy("host").agg(F.collect_list(F.struct("inner", "outer", "gap", "n")).alias("met"))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: dict[str, list] = {"classes": [], "spare": []}
            for row in batch.to_pylist():
                classes = resolved(row["classes"] or [], row["pages"] or [], {(m["inner"], m["outer"], m["gap"]): m["n"] for m in row["met"] or []})
                out["classes"].append(classes)
                out["spare"].append(sorted(set(row["often"]) - {r for members in classes for r in members}))
            yield pa.RecordBatch.from_arrays([
                batch.column(0), batch.column(1), pa.array(out["classes"], pa.list_(pa.list_(pa.int64()))), pa.array(out["spare"], pa.list_(pa.int64())), pa.array([len(r) for r in batch.column(2).to_pylist()], pa.int64()),
            ], names=["host", "n", "classes", "spare", "roles"])

    every = often.groupBy("host").agg(F.collect_list("role").alias("often")).join(of, "host")
    found = every.join(ordered.select("host", "classes", "pages"), "host", "left").join(met, "host", "left").select("host", "n", "often", "classes", "pages", "met")
    return written(found.mapInArrow(work, "host string, n long, classes array<array<long>>, spare array<long>, roles long"), "nested")


def rounds(pages: DataFrame) -> DataFrame:
    """host, n, roles, rounds: what the rounds found for each host with a template, as an array of (round, classes, spare); pages: host, key, roles, written."""
    of = few(written(pages.groupBy("host").agg(F.count("*").alias("n")).where(f"n >= {PAGES}"), "hosts"), BROADCAST_HOSTS)
    done: list[DataFrame] = []
    while True:
        sums = _summed(pages, "host string, role long, x long, y long, pages long, first long", ["host", "role"], _vectors)
        if not done:
            sums = sums.where("pages >= 2")  # a role of one page is not on half of three or more
        sums = written(sums.join(of, "host"), "vectors")
        often = sums.where(f"pages >= if((role & 3) = {ARTICLE}, 1, {SUPPORT}) * n").drop("n").withColumn("old", F.lit(False))
        if done:
            before = done[-1]
            moving = written(sums.groupBy("host").count().join(before.select("host", "roles"), "host").where("count > roles").select("host"), "moving")
            if (many := moving.count()) == 0:
                break
            was = before.select("host", F.explode(F.flatten("classes")).alias("role"), F.lit(True).alias("was"))
            often = often.join(F.broadcast(moving) if many <= BROADCAST_HOSTS else moving, "host", "left_semi").join(was, ["host", "role"], "left").withColumn("old", F.coalesce("was", F.lit(False))).drop("was")
        found = _round(pages, often, of)
        done.append(found)
        changing = found.where("size(spare) > 0 and size(classes) > 0")
        if changing.isEmpty():
            break
        pages = written(_renamed(with_host(pages, changing)), "roles")
    by_round = reduce(DataFrame.unionByName, (f.withColumn("round", F.lit(i)) for i, f in enumerate(done)))
    return by_round.groupBy("host").agg(F.max("n").alias("n"), F.sum("roles").alias("roles"), F.sort_array(F.collect_list(F.struct("round", "classes", "spare"))).alias("rounds"))


def _renamed(pages: DataFrame) -> DataFrame:
    @releasing
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            states: dict[str, tuple] = {}
            out = []
            for i, (name, roles) in enumerate(zip(batch.column(0).to_pylist(), lists(batch.column(2)), strict=True)):
                if name not in states:
                    states[name] = _state(batch.column(3)[i].as_py(), batch.column(4)[i].as_py())
                out.append(renamed(roles, *states[name])[0])
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(out, pa.list_(pa.int64()))], names=["host", "key", "roles"])

    return pages.select("host", "key", "roles", "classes", "spare").mapInArrow(work, "host string, key long, roles array<long>")
