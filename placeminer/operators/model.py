"""Nets from places, and their files."""

from __future__ import annotations

import json
from collections import deque
from dataclasses import dataclass
from xml.sax.saxutils import escape, quoteattr

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.places import END, START

Names = tuple[tuple[str, ...], tuple[str, ...]]
Arc = tuple[str, str]


@dataclass
class Net:
    """Places p0.., a source and a sink place, one transition an activity."""

    places: dict[str, Names]
    transitions: list[str]
    silent: frozenset[str] = frozenset()

    def arcs(self) -> list[tuple[str, str, str]]:
        """(from, to, kind) with kind ``produce`` for transition to place and ``consume`` for place to transition."""
        out = [("source", START, "consume"), (END, "sink", "produce")]
        for name, (pre, post) in self.places.items():
            out += [(a, name, "produce") for a in pre] + [(name, a, "consume") for a in post]
        return out

    def inputs(self) -> dict[str, list[str]]:
        out: dict[str, list[str]] = {t: [] for t in self.transitions}
        for a, b, kind in self.arcs():
            if kind == "consume":
                out[b].append(a)
        return out

    def outputs(self) -> dict[str, list[str]]:
        out: dict[str, list[str]] = {t: [] for t in self.transitions}
        for a, b, kind in self.arcs():
            if kind == "produce":
                out[a].append(b)
        return out


def to_net(places: list[Names], alphabet: list[str] = ()) -> Net:
    """The net of a place set (Q6). Activities outside of all places are free: they may occur at any time between the markers."""
    used = [a for p in places for side in p for a in side]
    inner = list(dict.fromkeys([*[a for a in used if a not in (START, END)], *[a for a in alphabet if a not in (START, END)]]))
    return Net({f"p{i}": p for i, p in enumerate(places)}, [START, *inner, END])


def closed_world(net: Net, alphabet: list[str]) -> Net:
    """Every activity between the markers only (Q7): one place filled by the start, looped by all, emptied by the end."""
    acts = tuple(sorted({*net.transitions, *alphabet} - {START, END}))
    free = tuple(sorted((START, *acts))), tuple(sorted((*acts, END)))
    return Net({**net.places, "free": free}, [START, *acts, END], net.silent)


def arcs_table(places: DataFrame) -> DataFrame:
    """src, dst, kind of a place table (place_id, pre, post), with the source and sink (Q6 in columns)."""
    made = places.select(F.explode("pre").alias("src"), F.col("place_id").alias("dst"), F.lit("produce").alias("kind"))
    used = places.select(F.col("place_id").alias("src"), F.explode("post").alias("dst"), F.lit("consume").alias("kind"))
    ends = places.sparkSession.createDataFrame([("source", START, "consume"), (END, "sink", "produce")], "src string, dst string, kind string")
    return made.union(used).union(ends)


def describe(net: Net, fits: dict[Names, float] | None = None) -> str:
    """Places as text, with their fitness if given (Q8)."""
    return "\n".join(f"{n}: {{{', '.join(p[0])}}} -> {{{', '.join(p[1])}}}" + (f" [{fits[p]:.3f}]" if fits and p in fits else "") for n, p in net.places.items())


def to_dot(net: Net) -> str:
    lines = ["digraph net {", "  rankdir=LR;", '  source [shape=circle, label="●"];', '  sink [shape=doublecircle, label=""];']
    lines += [f'  {n} [shape=circle, label=""];' for n in net.places]
    lines += [f"  {json.dumps(t, ensure_ascii=False)} [shape=box];" for t in net.transitions]
    lines += [f"  {json.dumps(a, ensure_ascii=False)} -> {json.dumps(b, ensure_ascii=False)};" for a, b, _ in net.arcs()]
    return "\n".join([*lines, "}"])


def to_pnml(net: Net, name: str = "net") -> str:
    ids = {t: f"t{i}" for i, t in enumerate(net.transitions)}
    out = ['<?xml version="1.0" encoding="UTF-8"?>', '<pnml xmlns="http://www.pnml.org/version-2009/grammar/pnml">', f'<net id={quoteattr(name)} type="http://www.pnml.org/version-2009/grammar/ptnet"><page id="page">']
    for p in ("source", "sink", *net.places):
        mark = "<initialMarking><text>1</text></initialMarking>" if p == "source" else ""
        out.append(f'<place id="{p}"><name><text>{p}</text></name>{mark}</place>')
    for t, i in ids.items():
        out.append(f'<transition id="{i}"><name><text>{escape(t)}</text></name></transition>')
    for k, (a, b, _) in enumerate(net.arcs()):
        out.append(f'<arc id="a{k}" source="{ids.get(a, a)}" target="{ids.get(b, b)}"/>')
    return "\n".join([*out, "</page></net></pnml>"])


def from_pnml(text: str) -> list[Names]:
    """The places of a net that :func:`to_pnml` wrote."""
    import xml.etree.ElementTree as ET

    root = ET.fromstring(text.encode())
    tag = lambda e: e.tag.rpartition("}")[2]
    label = {t.get("id"): "".join(t.itertext()).strip() for t in root.iter() if tag(t) == "transition"}
    order = [p.get("id") for p in root.iter() if tag(p) == "place" and p.get("id") not in ("source", "sink")]
    sides: dict[str, tuple[list, list]] = {p: ([], []) for p in order}
    for arc in (a for a in root.iter() if tag(a) == "arc"):
        a, b = arc.get("source"), arc.get("target")
        if b in sides:
            sides[b][0].append(label[a])
        elif a in sides:
            sides[a][1].append(label[b])
    return [(tuple(sorted(i)), tuple(sorted(o))) for i, o in (sides[p] for p in order)]


def to_json(net: Net, config: dict | None = None) -> str:
    return json.dumps({"places": [[list(a), list(b)] for a, b in net.places.values()], "transitions": net.transitions, "config": config or {}}, ensure_ascii=False)


def from_json(text: str) -> tuple[list[Names], dict]:
    d = json.loads(text)
    return [(tuple(a), tuple(b)) for a, b in d["places"]], d["config"]


def tables(spark: SparkSession, net: Net) -> dict[str, DataFrame]:
    """places, transitions, arcs and marking as DataFrames, for Parquet or SQL."""
    return {
        "places": spark.createDataFrame([(n, list(a), list(b)) for n, (a, b) in net.places.items()], "place_id string, pre array<string>, post array<string>"),
        "transitions": spark.createDataFrame([(t, t, t in net.silent) for t in net.transitions], "act string, label string, silent boolean"),
        "arcs": spark.createDataFrame(net.arcs(), "src string, dst string, kind string"),
        "marking": spark.createDataFrame([("source", 1, 0), ("sink", 0, 1)], "place string, init int, final int"),
    }


def diff(a: list[Names], b: list[Names]) -> dict[str, list[Names]]:
    """Places in both, only in the first, only in the second."""
    return {"both": sorted(set(a) & set(b)), "first": sorted(set(a) - set(b)), "second": sorted(set(b) - set(a))}


def enabled(net: Net, marking: dict[str, int]) -> list[str]:
    return [t for t, need in net.inputs().items() if all(marking.get(p, 0) >= 1 for p in need)]


def fire(net: Net, marking: dict[str, int], t: str) -> dict[str, int]:
    out = dict(marking)
    for p in net.inputs()[t]:
        out[p] -= 1
    for p in net.outputs()[t]:
        out[p] = out.get(p, 0) + 1
    return {p: n for p, n in out.items() if n}


def deadlocks(net: Net, limit: int = 10_000, bound: int | None = None) -> list[dict[str, int]]:
    """Reachable markings from which nothing can fire although the end is not reached (V14), among the first ``limit``."""
    return explored(net, limit, bound)[0]


def explored(net: Net, limit: int = 10_000, bound: int | None = None) -> tuple[list[dict[str, int]], bool]:
    """The deadlocks found, and whether every reachable marking was seen; ``bound`` leaves out markings with more tokens on a place."""
    whole = True
    start = {"source": 1}
    seen, queue, dead = {tuple(sorted(start.items()))}, deque([start]), []
    while queue and len(seen) < limit:
        m = queue.popleft()
        if m.get("sink"):
            continue
        can = [t for t in enabled(net, m) if t == START or "source" not in m]
        if not can:
            dead.append(m)
        for t in can:
            n = fire(net, m, t)
            key = tuple(sorted(n.items()))
            if bound is not None and max(n.values(), default=0) > bound:
                whole = False
            elif key not in seen:
                seen.add(key)
                queue.append(n)
    return dead, whole and not queue
