"""Trees and kernel machines trained on all rows of a table, for training sets that are too large for one task.

A tree grows by levels. Nodes of more than `local` rows take their cuts from counts of (feature, value, class) over all rows:
the cells are dealt out by ranges of values, a first pass gives each range the counts before it, a second one every cut's
gain, so no task holds a feature. The rows of smaller nodes travel to one task, which grows the rest. The tree is that of
`C45Tree` on all rows at once, thresholds and pruning included.

A kernel machine's Newton steps need sums of squares over all rows only: partial sums in each task, a pair's system solved
where they meet, and weights to the driver. Nystroem landmarks are the training rows of least hash of each class.
"""

from __future__ import annotations

import pickle
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fuzzyfeat.operators.design import View
from fuzzyfeat.operators.learners.data import Frame
from fuzzyfeat.operators.learners.svm import EXACT_ROWS, KernelSVM
from fuzzyfeat.operators.learners.tree import C45Tree, Node
from fuzzyfeat.session import scratch

Job = tuple[int, int]  # cluster count, and the fold that is left out; -1: none
CELLS, SUMS = 500_000, 4_000_000  # cells of a task's range, and numbers that a task sums up at once
CELL = "g int, v double, y int, w double"


def places(tree: C45Tree, frame: Frame, rows: np.ndarray) -> Iterator[tuple[Node, np.ndarray, np.ndarray]]:
    """(leaf, rows, their weights): an unknown value sends its row down all branches in proportion."""

    def send(node: Node, rows: np.ndarray, weight: np.ndarray):
        if not len(rows):
            return
        if not node.children:
            yield node, rows, weight
            return
        if node.feature < tree.n_num:
            x = frame.num[rows, node.feature]
            branch = np.where(np.isnan(x), -1, (x > node.threshold).astype(int))
        else:
            branch = np.maximum(frame.cat[rows, node.feature - tree.n_num], -1)
        total, lost = sum(c.counts.sum() for c in node.children.values()), branch < 0
        for b, child in node.children.items():
            own = branch == b
            if lost.any():
                part = weight * np.where(lost, child.counts.sum() / total, 1.0)
                own = own | lost
                yield from send(child, rows[own], part[own])
            else:
                yield from send(child, rows[own], weight[own])

    yield from send(tree.root, rows, np.ones(len(rows)))


def grow_trees(rows: DataFrame, view: View, jobs: list[Job], make: Callable[[], C45Tree], n_classes: int, local: int) -> dict[Job, C45Tree]:
    """A tree of each job on rows (id, r, x, s, y, fold): read once a level, once for the small nodes and once for the thresholds."""
    spark, counts = rows.sparkSession, sorted({k for k, _ in jobs})
    sizes = {(r["y"], r["fold"]): r["count"] for r in rows.groupBy("y", "fold").count().collect()}
    trees: dict[Job, C45Tree] = {}
    waiting: dict[int, tuple[Job, Node, int, frozenset]] = {}  # big nodes by mark
    small: dict[int, tuple[Job, Node, int, frozenset]] = {}
    marks = 0

    def leaf(job: Job, counts: np.ndarray, depth: int, used: frozenset) -> Node:
        """A new node, which waits for its split if it may have one."""
        nonlocal marks
        node = Node(counts)
        node.mark, marks = marks, marks + 1
        if not trees[job].ends(counts, depth):
            (waiting if counts.sum() > local else small)[node.mark] = (job, node, depth, used)
        return node

    for k, fold in jobs:
        tree = trees[k, fold] = make()
        tree.n_classes, tree.n_num = n_classes, view.empty(k).num.shape[1]
        tree.root = leaf((k, fold), np.array([float(sum(n for (y, f), n in sizes.items() if y == c and f != fold)) for c in range(n_classes)]), 0, frozenset())
    while waiting:
        now, waiting = waiting, {}
        with scratch(spark) as keep:
            found = _level(rows, view, trees, now, n_classes, keep)
        for mark, (job, node, depth, used) in now.items():
            if mark not in found:
                continue
            _, _, (below, parts), f = C45Tree.choose(found[mark])
            node.feature, symbolic = f, f >= trees[job].n_num
            node.threshold = node.below = below
            known = sum(parts.values())
            for b, part in parts.items():
                node.children[b] = leaf(job, part + (node.counts - known) * (part.sum() / known.sum()), depth + 1, used | ({f} if symbolic else set()))
    for mark, root in _subtrees(rows, view, trees, small, make, n_classes).items():
        node = small[mark][1]
        node.feature, node.threshold, node.below, node.children = root.feature, root.threshold, root.below, root.children
    _thresholds(rows, view, trees, counts)
    for tree in trees.values():
        if tree.prune:
            tree._prune(tree.root)
    return trees


def _level(rows: DataFrame, view: View, trees: dict[Job, C45Tree], now: dict[int, tuple], n_classes: int, keep) -> dict[int, list[tuple]]:
    """mark -> (gain, ratio, (value below the cut, class counts of each branch), feature) of each feature that may split the node."""
    spark, at = rows.sparkSession, {}
    groups: list[tuple[int, int]] = []
    for mark, (job, _, _, used) in now.items():
        width = trees[job].n_num + view.empty(job[0]).cat.shape[1]
        for f in range(width):
            if f not in used:
                at[mark, f] = len(groups)
                groups.append((mark, f))
    live = {job: trees[job] for job, *_ in now.values()}
    shared = spark.sparkContext.broadcast((view, live, at))

    def cells(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        view, live, at = shared.value
        for frames, y, fold, _ in view.blocks(batches, sorted({k for k, _ in live})):
            for (k, out), tree in live.items():
                for node, own, weight in places(tree, frames[k], np.flatnonzero(fold != out)):
                    for f in range(tree.n_num + frames[k].cat.shape[1]):
                        if (node.mark, f) not in at:
                            continue
                        v = frames[k].num[own, f] if f < tree.n_num else frames[k].cat[own, f - tree.n_num].astype(float)
                        known = ~np.isnan(v) if f < tree.n_num else v >= 0
                        values, code = np.unique(v[known] + 0.0, return_inverse=True)
                        table = np.bincount(code * n_classes + y[own][known], weight[known], len(values) * n_classes)
                        some = np.flatnonzero(table)
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(some), at[node.mark, f], np.int32)), pa.array(values[some // n_classes]), pa.array((some % n_classes).astype(np.int32)), pa.array(table[some])], ["g", "v", "y", "w"])

    summed = rows.mapInArrow(cells, CELL).groupBy("g", "v", "y").agg(F.sum("w").alias("w"))
    table = keep(summed)
    ranges = max(1, -(-table.count() // CELLS))
    table = keep(table.repartitionByRange(ranges, "g", "v").withColumn("part", F.spark_partition_id()))
    totals: dict[int, dict[int, np.ndarray]] = {}  # group -> range -> class counts
    for r in table.groupBy("g", "part", "y").agg(F.sum("w").alias("w")).collect():
        totals.setdefault(r["g"], {}).setdefault(r["part"], np.zeros(n_classes))[r["y"]] = r["w"]
    whole = {g: sum(by[p] for p in sorted(by)) for g, by in totals.items()}
    before = {(g, p): sum((by[o] for o in by if o < p), np.zeros(n_classes)) for g, by in totals.items() for p in by}
    numeric = {g: trees[now[mark][0]] for g, (mark, f) in enumerate(groups) if f < trees[now[mark][0]].n_num}
    least = {g: C45Tree(min_leaf=tree.min_leaf) for g, tree in numeric.items()}
    known = spark.sparkContext.broadcast((before, whole, least))

    def cuts(part: pa.Table) -> pa.Table:
        before, whole, least = known.value
        p = part.column("part")[0].as_py()
        g, v, y, w = (part.column(c).to_numpy() for c in ("g", "v", "y", "w"))
        out = []
        for one in np.unique(g):
            own = g == one
            values, code = np.unique(v[own], return_inverse=True)
            left = before[one, p] + np.cumsum(np.bincount(code * n_classes + y[own], w[own], len(values) * n_classes).reshape(-1, n_classes), axis=0)
            gain, valid = least[one].cut_gains(left, whole[one])
            if valid.any():
                best = int(gain.argmax())
                out.append((int(one), int(valid.sum()), float(gain[best]), float(values[best]), left[best].tolist()))
        return pa.Table.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True) if out else [[]] * 5, (pa.int32(), pa.int64(), pa.float64(), pa.float64(), pa.list_(pa.float64())), strict=True)], ["g", "n", "gain", "v", "left"])

    kinds = spark.createDataFrame([(g,) for g in numeric] or [(-1,)], "g int")
    found: dict[int, list[tuple]] = {}
    best: dict[int, list] = {}
    for r in table.join(F.broadcast(kinds), "g", "left_semi").groupBy("part").applyInArrow(cuts, "g int, n long, gain double, v double, left array<double>").collect():
        best.setdefault(r["g"], []).append(r)
    for g, own in best.items():
        mark, f = groups[g]
        counts, first = now[mark][1].counts, min(own, key=lambda r: (-r["gain"], r["v"]))
        left = np.array(first["left"])
        option = C45Tree.scored(first["gain"], sum(r["n"] for r in own), left, whole[g], whole[g].sum() / counts.sum(), counts.sum(), (first["v"], {0: left, 1: whole[g] - left}))
        if option:
            found.setdefault(mark, []).append((*option, f))
    levels: dict[int, dict[int, np.ndarray]] = {}
    for r in table.join(F.broadcast(kinds), "g", "left_anti").collect():  # as many as the feature has levels and classes
        levels.setdefault(r["g"], {}).setdefault(int(r["v"]), np.zeros(n_classes))[r["y"]] = r["w"]
    for g, by in levels.items():
        mark, f = groups[g]
        job, node, *_ = now[mark]
        by = {b: by[b] for b in sorted(by)}
        option = trees[job]._branches(np.array(list(by.values())), whole[g].sum() / node.counts.sum(), node.counts.sum())
        if option:
            found.setdefault(mark, []).append((*option[:2], (0.0, by), f))
    return {mark: sorted(options, key=lambda o: o[3]) for mark, options in found.items()}


def _subtrees(rows: DataFrame, view: View, trees: dict[Job, C45Tree], small: dict[int, tuple], make: Callable[[], C45Tree], n_classes: int) -> dict[int, Node]:
    """The rest of the tree below each small node, grown in one task of all the node's rows."""
    live = {job: trees[job] for job, *_ in small.values()}
    if not live:
        return {}
    settings = {mark: (depth, used) for mark, (_, _, depth, used) in small.items()}
    shared = rows.sparkSession.sparkContext.broadcast((view, live, settings))

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        view, live, settings = shared.value
        for frames, y, fold, part in view.blocks(batches, sorted({k for k, _ in live})):
            for (k, out), tree in live.items():
                for node, own, weight in places(tree, frames[k], np.flatnonzero(fold != out)):
                    if node.mark in settings:
                        lists = [pa.ListArray.from_arrays(np.arange(len(own) + 1, dtype=np.int32) * a.shape[1], pa.array(a[own].ravel())) for a in (frames[k].num, frames[k].cat.astype(np.int32))]
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(own), node.mark, np.int32)), part.column("id").take(pa.array(own)), *lists, pa.array(y[own].astype(np.int32)), pa.array(weight)], ["mark", "id", "num", "cat", "y", "w"])

    def grow(part: pa.Table) -> pa.Table:
        mark = part.column("mark")[0].as_py()
        part = part.sort_by("id")  # the same rows in the same order, however they arrived
        num, cat = (np.concatenate([np.asarray(c.flatten()) for c in part.column(n).chunks]).reshape(len(part), -1) for n in ("num", "cat"))
        depth, used = shared.value[2][mark]
        frame = Frame(num.astype(float), cat.astype(np.int64), [""] * num.shape[1], [""] * cat.shape[1])
        tree = make().fit(frame, part.column("y").to_numpy().astype(np.int64), n_classes, part.column("w").to_numpy(), depth, used)
        return pa.Table.from_arrays([pa.array([mark], pa.int32()), pa.array([pickle.dumps(tree.root)], pa.binary())], ["mark", "root"])

    sent = rows.mapInArrow(send, "mark int, id string, num array<double>, cat array<int>, y int, w double")
    return {r["mark"]: pickle.loads(r["root"]) for r in sent.groupBy("mark").applyInArrow(grow, "mark int, root binary").collect()}


def _thresholds(rows: DataFrame, view: View, trees: dict[Job, C45Tree], counts: list[int]) -> None:
    """Every threshold becomes the midpoint between the value below it and the next one among all training rows."""
    cuts: dict[tuple[int, int, int], set] = {}
    numeric: list[tuple[tuple[int, int, int], Node]] = []

    def visit(job: Job, node: Node) -> None:
        if node.children and node.feature < trees[job].n_num:
            numeric.append(((*job, node.feature), node))
            cuts.setdefault((*job, node.feature), set()).add(node.below)
        for child in node.children.values():
            visit(job, child)

    for job, tree in trees.items():
        visit(job, tree.root)
    wanted = {key: np.array(sorted(values)) for key, values in cuts.items()}
    shared = rows.sparkSession.sparkContext.broadcast((view, wanted))

    def nearest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        view, wanted = shared.value
        least = {key: np.full(len(values), np.inf) for key, values in wanted.items()}
        for frames, _, fold, _ in view.blocks(batches, counts):
            for (k, out, f), values in wanted.items():
                x = frames[k].num[fold != out, f]
                x = np.append(np.sort(x[~np.isnan(x)]), np.inf)
                least[k, out, f] = np.minimum(least[k, out, f], x[np.searchsorted(x[:-1], values, "right")])
        for (k, out, f), found in least.items():
            n = len(found)
            yield pa.RecordBatch.from_arrays([*(pa.array(np.full(n, c, np.int32)) for c in (k, out, f)), pa.array(np.arange(n, dtype=np.int32)), pa.array(found)], ["k", "fold", "f", "i", "next"])

    found = {key: values.copy() for key, values in wanted.items()}
    if wanted:
        for r in rows.mapInArrow(nearest, "k int, fold int, f int, i int, next double").groupBy("k", "fold", "f", "i").agg(F.min("next").alias("next")).collect():
            found[r["k"], r["fold"], r["f"]][r["i"]] = r["next"]
    for key, node in numeric:
        node.threshold = float((node.below + found[key][np.searchsorted(wanted[key], node.below)]) / 2)


def fit_machines(rows: DataFrame, view: View, jobs: list[Job], make: Callable[[], KernelSVM], n_classes: int) -> dict[Job, KernelSVM]:
    """A kernel machine of each job on rows (id, r, x, s, y, fold): one scan for the scales, one for landmarks, and one for each Newton step of a group of jobs."""
    counts = sorted({k for k, _ in jobs})
    machines, scales = {job: make() for job in jobs}, _scales(rows, view, counts, n_classes)
    for (k, fold), m in machines.items():
        own = [v for (kk, f), v in scales.items() if kk == k and f != fold]
        low, high, levels, sizes = np.min([o[0] for o in own], axis=0), np.max([o[1] for o in own], axis=0), np.max([o[2] for o in own], axis=0), np.sum([o[3] for o in own], axis=0)
        m.scale(n_classes, np.nan_to_num(low, posinf=0.0), np.nan_to_num(high, neginf=0.0), [int(n) for n in levels], sizes)
        m.approx = m.asked or m.choose(EXACT_ROWS + 1, len(low) + int(levels.sum()))
        if m.approx == "exact":
            raise ValueError("the kernel matrix of all rows is asked for, and they are too many for it")
    if any(m.approx == "nystrom" for m in machines.values()):
        for job, (frame, y) in _landmarks(rows, view, jobs, {job: max(1, m.features // max(1, len(m.present))) for job, m in machines.items()}).items():
            machines[job].basis(frame, y)
    for job, m in machines.items():
        if m.approx == "rff":
            m.basis(view.empty(job[0]), np.zeros(0, np.int64))
        m.models = []
    group: list[Job] = []
    size = lambda job: len(machines[job].pairs) * machines[job].columns(view.empty(job[0])) ** 2
    for job in [*machines, None]:
        if group and (job is None or sum(map(size, group)) + size(job) > SUMS):
            _newton(rows, view, {j: machines[j] for j in group})
            group = []
        group.append(job)
    return machines


def _scales(rows: DataFrame, view: View, counts: list[int], n_classes: int) -> dict[Job, tuple]:
    """(count, fold) -> least and greatest numeric values, numbers of levels, and class sizes of the fold's rows."""
    shared = rows.sparkSession.sparkContext.broadcast(view)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[Job, tuple] = {}
        for frames, y, fold, _ in shared.value.blocks(batches, counts):
            for k, frame in frames.items():
                for f in np.unique(fold):
                    own = fold == f
                    num, cat = frame.num[own], frame.cat[own]
                    low, high = np.where(np.isnan(num), np.inf, num).min(axis=0), np.where(np.isnan(num), -np.inf, num).max(axis=0)
                    new = (low, high, np.maximum(cat.max(axis=0, initial=-1), -1) + 1.0, np.bincount(y[own], minlength=n_classes).astype(float))
                    old = held.get((k, int(f)))
                    held[k, int(f)] = new if old is None else (np.minimum(old[0], low), np.maximum(old[1], high), np.maximum(old[2], new[2]), old[3] + new[3])
        for (k, f), parts in held.items():
            yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([f], pa.int32()), *(pa.array([p.tolist()], pa.list_(pa.float64())) for p in parts)], ["k", "fold", "low", "high", "levels", "sizes"])

    out: dict[Job, tuple] = {}
    for r in rows.mapInArrow(work, "k int, fold int, low array<double>, high array<double>, levels array<double>, sizes array<double>").collect():
        new, old = tuple(np.array(r[c], float) for c in ("low", "high", "levels", "sizes")), out.get((r["k"], r["fold"]))
        out[r["k"], r["fold"]] = new if old is None else (np.minimum(old[0], new[0]), np.maximum(old[1], new[1]), np.maximum(old[2], new[2]), old[3] + new[3])
    return out


def _landmarks(rows: DataFrame, view: View, jobs: list[Job], most: dict[Job, int]) -> dict[Job, tuple[Frame, np.ndarray]]:
    """Of each job, the training rows of least (hash, id) of each class: a fold's own rows are never among them."""
    folds = [r[0] for r in rows.select("fold").distinct().collect()]
    classes = [r[0] for r in rows.select("y").distinct().collect()]
    mark = F.xxhash64(F.lit("landmark"), "id")
    near = [r for y in classes for f in folds for r in rows.filter((F.col("y") == y) & (F.col("fold") == f)).orderBy(mark, "id").limit(max(most.values())).withColumn("m", mark).collect()]
    near.sort(key=lambda r: (r["y"], r["m"], r["id"]))
    out = {}
    for k, fold in jobs:
        own = [r for c in sorted(classes) for r in [r for r in near if r["y"] == c and r["fold"] != fold][: most[k, fold]]]
        r, x, s = (np.array([o[c] for o in own], t).reshape(len(own), -1) for c, t in (("r", float), ("x", float), ("s", np.int64)))
        out[k, fold] = (view.frame(k, r, x, s), np.array([o["y"] for o in own]))
    return out


def _newton(rows: DataFrame, view: View, machines: dict[Job, KernelSVM], steps: int = 12) -> None:
    """The weights of every pair of classes: a step solves with the rows inside the margin of the step before, until these stay the same."""
    spark, C = rows.sparkSession, next(iter(machines.values())).C
    weights: dict[tuple, list] = {(*job, a, b): [None, None] for job, m in machines.items() for a, b in m.pairs}  # of the last two steps
    live, bare = set(weights), {job: pickle.dumps(m) for job, m in machines.items()}
    for _ in range(steps):
        shared = spark.sparkContext.broadcast((view, bare, {key: weights[key] for key in live}))

        def sums(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            view, bare, weights = shared.value
            machines = {job: pickle.loads(m) for job, m in bare.items() if any(key[:2] == job for key in weights)}
            held: dict[tuple, list] = {}
            for frames, y, fold, _ in view.blocks(batches, sorted({k for k, _ in machines})):
                for (k, out), m in machines.items():
                    train = np.flatnonzero(fold != out)
                    z, c = m.mapped(frames[k].rows(train)), y[train]
                    for key, (older, last) in weights.items():
                        if key[:2] != (k, out):
                            continue
                        _, _, a, b = key
                        own = np.flatnonzero((c == a) | (c == b)) if b >= 0 else np.arange(len(c))
                        t, zz = np.where(c[own] == a, 1.0, -1.0), z[own]
                        active = np.ones(len(t), bool) if last is None else t * (zz @ last) < 1
                        moved = len(t) if last is None else int((active != (np.ones(len(t), bool) if older is None else t * (zz @ older) < 1)).sum())
                        za = zz[active]
                        new = [za.T @ za, za.T @ t[active], moved]
                        held[key] = new if key not in held else [o + n for o, n in zip(held[key], new, strict=True)]
            for key, (square, cross, moved) in held.items():
                yield pa.RecordBatch.from_arrays([*(pa.array([c], pa.int32()) for c in key), pa.array([square.tobytes()], pa.binary()), pa.array([cross.tobytes()], pa.binary()), pa.array([moved], pa.int64())], ["k", "fold", "a", "b", "square", "across", "moved"])

        def solve(part: pa.Table) -> pa.Table:
            crosses = [np.frombuffer(x.as_py()) for x in part.column("across")]
            d = len(crosses[0])
            ridge = np.eye(d)
            ridge[-1, -1] = 1e-8
            square = sum(np.frombuffer(x.as_py()).reshape(d, d) for x in part.column("square"))
            w = np.linalg.solve(ridge / 2 + C * square, C * sum(crosses))
            return pa.Table.from_arrays([*(part.column(c).slice(0, 1) for c in ("k", "fold", "a", "b")), pa.array([w.tolist()], pa.list_(pa.float64())), pa.array([sum(part.column("moved").to_pylist())], pa.int64())], ["k", "fold", "a", "b", "w", "moved"])

        partial = rows.mapInArrow(sums, "k int, fold int, a int, b int, square binary, across binary, moved long")
        for r in partial.groupBy("k", "fold", "a", "b").applyInArrow(solve, "k int, fold int, a int, b int, w array<double>, moved long").collect():
            key = (r["k"], r["fold"], r["a"], r["b"])
            if weights[key][1] is not None and r["moved"] == 0:
                live.discard(key)
            else:
                weights[key] = [weights[key][1], np.array(r["w"])]
        if not live:
            break
    for job, m in machines.items():
        m.models = [(a, b if b >= 0 else None, weights[*job, a, b][1]) for a, b in m.pairs]


def verdicts(rows: DataFrame, view: View, models: dict[Job, object]) -> dict[Job, tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(true classes, said ones, how many rows) of each job on the rows of its fold: one scan."""
    shared = rows.sparkSession.sparkContext.broadcast((view, models))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        view, models = shared.value
        held: dict[tuple, int] = {}
        for frames, y, fold, _ in view.blocks(batches, sorted({k for k, _ in models})):
            for (k, out), model in models.items():
                test = np.flatnonzero(fold == out)
                if len(test):
                    cells, times = np.unique(np.stack([y[test], model.predict(frames[k].rows(test))], axis=1), axis=0, return_counts=True)
                    for (a, b), n in zip(cells.tolist(), times.tolist(), strict=True):
                        held[k, out, a, b] = held.get((k, out, a, b), 0) + n
        if held:
            cells = [(*key, n) for key, n in held.items()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*cells, strict=True), (pa.int32(),) * 4 + (pa.int64(),), strict=True)], ["k", "fold", "y", "said", "n"])

    found: dict[Job, list] = {}
    for r in rows.mapInArrow(work, "k int, fold int, y int, said int, n long").groupBy("k", "fold", "y", "said").agg(F.sum("n").alias("n")).collect():
        found.setdefault((r["k"], r["fold"]), []).append((r["y"], r["said"], r["n"]))
    return {job: tuple(np.array(c, np.int64) for c in zip(*cells, strict=True)) for job, cells in found.items()}
