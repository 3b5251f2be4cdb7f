"""One owner's share of a fused round, over Arrow columns.

Ids become dense positions, edges compressed rows; a frontier is expanded by index arithmetic and
folded by scatter.  Values written in one local round are read in the next.  There is no per-row
Python; memory is bounded by one owner's edges, which the number of owners sets.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa

SCHEMA = "kind int, part int, id long, val long, more boolean, generated long, local long, remote_raw long, queued long, accepted long, rounds long, batches long, edge_gets long"
STATE, MAIL, COUNTS = 0, 1, 2

def _plus(v: np.ndarray, w: np.ndarray) -> np.ndarray:
    out = v + w
    if np.any((w >= 0) & (out < v)):
        raise OverflowError("a distance exceeds 64 bits")
    return out


#: Candidate values over (value of the source, weight), the NumPy twins of the Column expressions.
KERNELS: dict[str, Callable] = {"plus_weight": _plus, "same": lambda v, w: v, "plus_one": lambda v, w: v + 1, "least_with_weight": lambda v, w: np.minimum(v, w)}


def _expand(heads: np.ndarray, start: np.ndarray, stop: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Edge numbers of the given heads, and for each the place of its head in ``heads``."""
    n = stop[heads] - start[heads]
    owner = np.repeat(np.arange(len(heads)), n)
    ahead = np.concatenate([[0], np.cumsum(n)[:-1]]) if len(n) else n
    return start[heads][owner] + np.arange(n.sum()) - ahead[owner], owner


def pulse(part: int, state: pa.Table, edges: pa.Table, kernel: str, at: Callable, worst: int, max_rounds: int | None, batch_size: int) -> pa.Table:
    """Run the frontier to exhaustion (or ``max_rounds``) on local targets; queue the best for foreign ones."""
    state = state.filter(state.column("val").is_valid())
    sid, sval = state.column("id").to_numpy(), state.column("val").to_numpy()
    active = state.column("changed").to_numpy(zero_copy_only=False).astype(bool)
    if not active.any():  # an idle owner: nothing to index
        return _told(part, *[np.empty(0, np.int64)] * 6, [0] * 8)
    src, dst = edges.column("src").to_numpy(), edges.column("dst").to_numpy()
    home, w = edges.column("dst_part").to_numpy(), edges.column("w").to_numpy()
    if max_rounds == 1:  # only the frontier's edges are used: index no others
        used = np.isin(src, sid[active])
        src, dst, home, w = src[used], dst[used], home[used], w[used]
    mine = home == part
    ids = np.unique(np.concatenate([sid, src, dst[mine]]))
    value = np.full(len(ids), worst, np.int64)
    where = np.searchsorted(ids, sid)
    value[where] = sval
    before = value.copy()
    head = np.searchsorted(ids, src)
    order = np.argsort(head, kind="stable")
    head, dst, home, w, mine = head[order], dst[order], home[order], w[order], mine[order]
    start, stop = np.searchsorted(head, np.arange(len(ids))), np.searchsorted(head, np.arange(len(ids)), side="right")
    target = np.full(len(dst), -1)
    target[mine] = np.searchsorted(ids, dst[mine])
    far, slot = np.unique(dst[~mine], return_inverse=True)
    far_home = np.zeros(len(far), np.int64)
    far_home[slot] = home[~mine]
    place = np.full(len(dst), -1)
    place[~mine] = slot
    best = np.full(len(far), worst, np.int64)
    touched = np.zeros(len(far), bool)
    front = np.sort(where[active])
    generated = local = raw = accepted = rounds = 0
    step = KERNELS[kernel]
    while len(front) and (max_rounds is None or rounds < max_rounds):
        rounds += 1
        e, owner = _expand(front, start, stop)
        candidate = step(value[front][owner], w[e])
        near = mine[e]
        generated += len(e)
        local += int(near.sum())
        raw += int((~near).sum())
        at(best, place[e[~near]], candidate[~near])
        touched[place[e[~near]]] = True
        new = value.copy()
        at(new, target[e[near]], candidate[near])
        front = np.flatnonzero(new != value)
        accepted += len(front)
        value = new
    moved = np.flatnonzero(value != before)
    carried = np.zeros(len(ids), bool)
    carried[front] = True
    moved = np.union1d(moved, front)
    send = np.flatnonzero(touched)
    per = np.unique(far_home[send], return_counts=True)[1]
    counts = [generated, local, raw, len(send), accepted, rounds, int(np.sum(-(-per // batch_size))), generated]
    return _told(part, ids[moved], value[moved], carried[moved], far_home[send], far[send], best[send], counts)


def _told(part: int, ids: np.ndarray, values: np.ndarray, carried: np.ndarray, homes: np.ndarray, targets: np.ndarray, best: np.ndarray, counts: list[int]) -> pa.Table:
    """State rows, mail rows and one row of counters."""
    n, m = len(ids), len(targets)
    zero = np.zeros(n + m, np.int64)
    columns = [
        np.concatenate([np.full(n, STATE), np.full(m, MAIL), [COUNTS]]).astype(np.int32), np.concatenate([np.full(n, part), homes, [part]]).astype(np.int32), np.concatenate([ids, targets, [0]]).astype(np.int64),
        np.concatenate([values, best, [0]]).astype(np.int64), np.concatenate([carried.astype(bool), np.zeros(m + 1, bool)]), *[np.append(zero, c) for c in counts],
    ]
    names = [f.split()[0] for f in SCHEMA.split(", ")]
    return pa.table(dict(zip(names, columns, strict=True)))


def remaining(state: pa.Table, edges: pa.Table, kernel: str, at: Callable, worst: int, mode: str, limit: int | None, max_rounds: int, batch_size: int) -> pa.Table:
    """All further rounds of all owners over whole columns: the values that vertices end with, and a row of counters for each round.

    Owners, mail and counters are those of the rounds in Spark; a round costs its frontier, not the graph.  The last row
    of counters has ``more`` if ``max_rounds`` came first.
    """
    src, dst, w = (edges.column(c).to_numpy() for c in ("src", "dst", "w"))
    ids, first = np.unique(state.column("id").to_numpy(), return_index=True)  # every vertex has a row
    part = state.column("part").to_numpy()[first].astype(np.int64)
    known = state.filter(state.column("val").is_valid())
    where = np.searchsorted(ids, known.column("id").to_numpy())
    value = np.full(len(ids), worst, np.int64)
    value[where] = known.column("val").to_numpy()
    front = np.sort(where[known.column("changed").to_numpy(zero_copy_only=False).astype(bool)])
    # edges lie in the order of target and sender, so what meets in one target is folded without a sort
    head, target = (np.searchsorted(ids, x) for x in (src, dst))
    order = np.lexsort((head, part[head], target))
    head, target, w = head[order], target[order], w[order]
    near = part[head] == part[target]
    fresh = np.concatenate([[True], (target[1:] != target[:-1]) | (part[head[1:]] != part[head[:-1]])])[: len(w)]
    entry = np.cumsum(fresh) - 1  # one for each sender and target
    parts = int(part.max()) + 1 if len(part) else 1
    entry_target, entry_ends = target[fresh], part[head[fresh]] * parts + part[target[fresh]]
    by_head = np.argsort(head, kind="stable")
    many, many_near = np.bincount(head, minlength=len(ids)), np.bincount(head[near], minlength=len(ids))
    stop = np.cumsum(many)
    start = stop - many
    into = np.concatenate([[0], np.cumsum(np.bincount(target, minlength=len(ids)))])
    low, high = np.full(len(ids), len(ids)), np.full(len(ids), -1)
    np.minimum.at(low, head, target)
    np.maximum.at(high, head, target)
    step, fold, mail_only = KERNELS[kernel], at.__self__, mode in ("uncombined", "plain")
    on = np.zeros(len(ids), bool)

    def leaving(front: np.ndarray, n: int) -> np.ndarray:
        """The ``n`` edges of the frontier in order: picked from all edges into the span of its targets, or sorted if they are few of those."""
        if not n:
            return np.empty(0, np.int64)
        a, b = into[low[front].min()], into[high[front].max() + 1]
        if b - a > 8 * n:
            return np.sort(by_head[_expand(front, start, stop)[0]])
        on[front] = True
        found = np.flatnonzero(on.take(head[a:b]))
        on[front] = False
        return found + a

    def folded(to: np.ndarray, val: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The best value of each run of equal ``to``."""
        ahead = np.flatnonzero(to[1:] != to[:-1])
        if len(ahead) == len(to) - 1:
            return to, val
        ahead = np.concatenate([[0], ahead + 1])
        return to.take(ahead), fold.reduceat(val, ahead)

    def improve(to: np.ndarray, val: np.ndarray) -> np.ndarray:
        if not len(to):
            return to
        to, val = folded(to, val)
        old = value.take(to)
        new = fold(old, val)
        value[to] = new
        return to[new != old]

    told = []
    while len(front) and len(told) < max_rounds:
        generated = local = accepted = rounds = 0
        mail: list[tuple[np.ndarray, np.ndarray]] = []
        while len(front) and (rounds < 1 if mail_only else limit is None or rounds < limit):
            rounds += 1
            n, own = int(many.take(front).sum()), int(many_near.take(front).sum())
            e = leaving(front, n)
            candidate = step(value.take(head.take(e)), w.take(e))
            generated += n
            local += own
            if mail_only:
                mail.append((entry.take(e), candidate))
                front = front[:0]
            elif own == n:
                front = improve(target.take(e), candidate)
            else:
                mine = near.take(e)
                mail.append((entry.take(e[~mine]), candidate[~mine]))
                front = improve(target.take(e[mine]), candidate[mine])
            accepted += len(front)
        sent, candidate = mail[0] if len(mail) == 1 else (np.concatenate(x) for x in zip((front[:0], front[:0]), *mail, strict=True))
        if len(mail) > 1:
            turn = np.argsort(sent, kind="stable")
            sent, candidate = sent[turn], candidate[turn]
        queued, by_mail = len(sent), front[:0]
        between = np.empty(0, np.int64)
        if queued:
            sent, candidate = folded(sent, candidate)
            queued = queued if mode == "uncombined" else len(sent)
            between = np.bincount(entry_ends.take(sent))
            by_mail = improve(entry_target.take(sent), candidate)
        front = np.union1d(by_mail, front) if len(front) else by_mail
        told.append([generated, local, generated - local, queued, accepted + len(by_mail), rounds, int(np.sum(-(-between // batch_size))), generated])
    done = np.flatnonzero(value != worst)
    n, m = len(done), len(told)
    counts = np.array(told, np.int64).reshape(m, 8)
    more = np.zeros(n + m, bool)
    more[-1:] = bool(len(front))
    columns = [
        np.repeat([STATE, COUNTS], [n, m]).astype(np.int32), np.concatenate([part[done], np.zeros(m, np.int64)]).astype(np.int32), np.concatenate([ids[done], np.arange(m)]),
        np.concatenate([value[done], np.zeros(m, np.int64)]), more, *[np.concatenate([np.zeros(n, np.int64), counts[:, k]]) for k in range(8)],
    ]
    return pa.table(dict(zip([f.split()[0] for f in SCHEMA.split(", ")], columns, strict=True)))
