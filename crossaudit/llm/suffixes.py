"""Repeated passages by sorting suffixes deep-shallow.

Every window of 50 bytes has an anchor: of its 31 substrings of 20 bytes the one with the least hash, so equal windows
have equal anchors, and neighbouring windows share theirs. Documents lie in groups of bounded size. First the anchors'
hashes of all groups meet, and each group learns which of its anchors another document has too; about 5 bytes an anchor are
shuffled. Only around those, each group sends its distinct snippets (the bytes of a run of windows with one anchor) to the bucket of
the anchor. There snippets that several groups sent are one, and all windows of the distinct ones are sorted as suffixes, deep-shallow:
to a shallow depth a multikey sort splits each tied group by its next eight bytes at once (numpy sorts words faster than it could partition three ways
by single characters, and the order is the same); groups that are still tied and differ further on go through blind tries. Equal windows
give the smallest document each occurs in, which goes back to the groups as runs.

Where there are more than ``cell`` groups, anchors meet in two steps, within cells of that many groups and then between cells, so no
task hears from all groups; and windows around an anchor that more than ``hot`` cells have are combined by Spark's own aggregation, one row a
window, instead of in the anchor's bucket.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from crossaudit.functions.storage import materialize

WINDOW = 50
ANCHOR = 20
SPAN = WINDOW - ANCHOR + 1
SNIPPET = WINDOW + SPAN - 1
SHALLOW = 32
#: Bytes of text in a group, about.
GROUP_BYTES = 2_500_000
#: Groups whose anchors meet in one place, and cells that may have an anchor before its windows go a way of their own.
CELL, HOT = 1000, 64
_CHUNK = 1 << 19
_LAST = (1 << 63) - 1
_M1, _M2, _M3, _M4 = (np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93))


def _loads(buffer: np.ndarray) -> np.ndarray:
    """The eight bytes from each place on, as little-endian integers."""
    n = len(buffer) - 7
    out = np.empty(max(0, n), np.uint64)
    for r in range(min(8, max(0, n))):
        part = buffer[r : r + (n - r + 7) // 8 * 8].view("<u8") if not r else np.frombuffer(buffer.data, "<u8", (n - r + 7) // 8, r)
        out[r::8] = part
    return out


def _hashes(buffer: np.ndarray) -> np.ndarray:
    """64-bit hashes of the substrings of 20 bytes from each place on."""
    u = _loads(buffer)
    n = len(buffer) - ANCHOR + 1
    h = u[:n] * _M1
    h ^= (u[8 : 8 + n] ^ (h >> np.uint64(31))) * _M2
    h ^= (u[12 : 12 + n] ^ (h >> np.uint64(29))) * _M3
    h ^= h >> np.uint64(32)
    h *= _M4
    h ^= h >> np.uint64(29)
    return h


def anchor_runs(buffer: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Runs of windows with one anchor: first window, number of windows, anchor's hash.

    ``buffer`` is the texts one after another, ``starts`` their starts and the end; windows stay inside texts.
    """
    firsts, counts, hashes = [], [], []
    low = np.uint64(_CHUNK * 2 - 1)
    for at in range(0, max(0, len(buffer) - WINDOW + 1), _CHUNK):
        piece = buffer[at : at + _CHUNK + WINDOW - 1]
        h = _hashes(piece)
        key = (h & ~low) | np.arange(len(h), dtype=np.uint64)
        m = np.minimum(key[:-1], key[1:])
        for step in (2, 4, 8):
            m = np.minimum(m[:-step], m[step:])
        m = np.minimum(m[: -(SPAN - 16)], m[SPAN - 16 :])  # of 16 and 31 places
        anchor = m & low
        new = np.ones(len(anchor), bool)
        np.not_equal(anchor[1:], anchor[:-1], out=new[1:])
        new[starts[np.searchsorted(starts, at) : np.searchsorted(starts, at + len(anchor))] - at] = True
        first = np.flatnonzero(new)
        # a run's windows are those that end inside its document
        doc = np.searchsorted(starts, first + at, side="right") - 1
        count = np.minimum(np.append(first[1:], len(anchor)), starts[doc + 1] - WINDOW + 1 - at) - first
        first, count = first[count > 0], count[count > 0]
        firsts.append(first + at)
        counts.append(count)
        hashes.append(h[anchor[first].astype(np.int64)])
    cat = lambda x, t: np.concatenate(x) if x else np.zeros(0, t)
    return cat(firsts, np.int64), cat(counts, np.int64), cat(hashes, np.uint64)


def distinct_rows(matrix: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """One place of each distinct row of a byte matrix, and for every row the number of its like among them.

    Rows are brought together by a hash and compared whole; should a hash collide, equal rows may count as several.
    """
    n, width = matrix.shape
    words = np.zeros((n, -(-width // 8) * 8), np.uint8)
    words[:, :width] = matrix
    words = words.view(np.uint64)
    h = np.zeros(n, np.uint64)
    for c in range(words.shape[1]):
        h = (h ^ words[:, c]) * _M1
        h ^= h >> np.uint64(29)
    order = np.argsort(h, kind="stable")
    new = np.ones(n, bool)
    new[1:] = h[order[1:]] != h[order[:-1]]
    like = np.flatnonzero(~new)
    new[like] = (words[order[like]] != words[order[like - 1]]).any(axis=1)
    number = np.empty(n, np.int64)
    number[order] = np.cumsum(new) - 1
    return order[new], number


def blind_trie(tails: list[bytes]) -> list[int]:
    """Rank of each string among the distinct ones, in order; strings have one length.

    A node holds only the place of the first byte in which its branches differ. A string goes down blindly, is
    compared once with the leaf it ends at, and branches off where it differs.
    """
    root: list | int = 0
    same: dict[int, int] = {}
    for k in range(1, len(tails)):
        t, node = tails[k], root
        while isinstance(node, list):
            node = node[1].get(t[node[0]], next(iter(node[1].values())))
        other = tails[node]
        if t == other:
            same[k] = node
            continue
        depth = next(i for i, (a, b) in enumerate(zip(t, other, strict=True)) if a != b)
        above, node = None, root
        while isinstance(node, list) and node[0] < depth:
            above, node = node, node[1][t[node[0]]]
        if isinstance(node, list) and node[0] == depth:
            node[1][t[depth]] = k
        else:
            branch = [depth, {other[depth]: node, t[depth]: k}]
            if above is None:
                root = branch
            else:
                above[1][t[above[0]]] = branch
    rank, out, stack = {}, 0, [root]
    while stack:
        node = stack.pop()
        if isinstance(node, list):
            stack += [node[1][c] for c in sorted(node[1], reverse=True)]
        else:
            rank[node] = out
            out += 1
    return [rank[same.get(k, k)] for k in range(len(tails))]


def sort_windows(data: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order of the windows of ``data`` that start at ``at``, and which of them (in order) begin a new distinct window."""
    eight = np.lib.stride_tricks.sliding_window_view(np.concatenate([data, np.zeros(8, np.uint8)]), 8)

    def word(places: np.ndarray) -> np.ndarray:
        return np.ascontiguousarray(eight[places]).view(">u8")[:, 0].astype(np.uint64)

    key = word(at)
    order = np.argsort(key, kind="stable")
    key = key[order]
    new = np.ones(len(at), bool)
    new[1:] = key[1:] != key[:-1]
    del key

    def tied() -> tuple[np.ndarray, np.ndarray]:
        """Places (in order) in groups of several, and their groups' numbers."""
        group = np.cumsum(new) - 1
        member = np.bincount(group)[group] > 1 if len(group) else np.zeros(0, bool)
        place = np.flatnonzero(member)
        return place, group[place]

    for depth in range(8, SHALLOW, 8):
        place, group = tied()
        if not len(place):
            return order, new
        key = word(at[order[place]] + depth)
        inner = np.lexsort((key, group))
        order[place] = order[place][inner]
        key, changed = key[inner], np.ones(len(place), bool)
        changed[1:] = (key[1:] != key[:-1]) | (group[1:] != group[:-1])
        new[place] = changed
    place, group = tied()
    if len(place):
        rest = at[order[place]] + SHALLOW
        differ = np.zeros(len(place), bool)
        for d in (0, 8, WINDOW - SHALLOW - 8):
            key = word(rest + d)
            differ[1:] |= key[1:] != key[:-1]
        differ[1:] &= group[1:] == group[:-1]
        heads = np.flatnonzero(np.diff(group, prepend=-1))
        mixed = np.add.reduceat(differ, heads) > 0
        ends = np.append(heads[1:], len(place))
        raw = data.tobytes()
        for a, b in zip(heads[mixed].tolist(), ends[mixed].tolist(), strict=True):
            own = order[place[a:b]]
            starts = at[own].tolist()
            rank = np.array(blind_trie([raw[s + SHALLOW : s + WINDOW] for s in starts]))
            inner = np.argsort(rank, kind="stable")
            order[place[a:b]] = own[inner]
            new[place[a:b]] = np.diff(rank[inner], prepend=-1) != 0
    return order, new


class Group:
    """The texts of one group, its runs of windows, and the distinct snippets around anchors known to be shared."""

    def __init__(self, table: pa.Table, buckets: int):
        # runs are cut where a chunk of the buffer ends, so every pass over a group must see its texts in one order
        table = table.select(["doc", "text"]).sort_by([("doc", "ascending"), ("text", "ascending")])
        texts = table.column("text").combine_chunks()
        texts = (texts.chunk(0) if isinstance(texts, pa.ChunkedArray) else texts).cast(pa.large_string()).fill_null("")
        ends = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1]
        body = texts.buffers()[2]
        self.buffer = np.frombuffer(body, np.uint8)[ends[0] : ends[-1]] if body is not None and len(texts) else np.zeros(0, np.uint8)
        self.starts = ends - ends[0] if len(texts) else np.zeros(1, np.int64)
        self.docs = table.column("doc").to_numpy()
        self.first, self.count, h = anchor_runs(self.buffer, self.starts)
        self.code = (h % np.uint64(buckets)).astype(np.int64) << 40 | (h >> np.uint64(24)).astype(np.int64)
        self.codes, self.place = np.unique(self.code, return_inverse=True)
        self.doc = self.docs[np.searchsorted(self.starts, self.first, side="right") - 1]

    def share(self, elsewhere: np.ndarray, hot: np.ndarray) -> None:
        """``elsewhere`` tells of each of ``codes`` whether another group has it, ``hot`` whether very many have."""
        low, high = np.full(len(self.codes), _LAST), np.full(len(self.codes), -_LAST - 1)
        np.minimum.at(low, self.place, self.doc)
        np.maximum.at(high, self.place, self.doc)
        self.runs = np.flatnonzero((elsewhere | (low < high))[self.place])
        n = self.count[self.runs]
        matrix = np.zeros((len(n), SNIPPET + 1), np.uint8)
        padded = np.concatenate([self.buffer, np.zeros(SNIPPET, np.uint8)])
        view = np.lib.stride_tricks.sliding_window_view(padded, SNIPPET)
        matrix[:, :SNIPPET] = view[self.first[self.runs]]
        matrix[:, :SNIPPET][np.arange(SNIPPET)[None, :] >= (n + WINDOW - 1)[:, None]] = 0
        matrix[:, SNIPPET] = n
        chosen, self.snippet = distinct_rows(matrix)
        self.snippets = matrix[chosen]
        self.snippet_bucket = self.code[self.runs[chosen]] >> 40
        self.hot = hot[self.place[self.runs[chosen]]]
        self.least = np.full(len(chosen), _LAST)
        np.minimum.at(self.least, self.snippet, self.doc[self.runs])

    def covered(self, index: np.ndarray, start: np.ndarray, length: np.ndarray, doc: np.ndarray) -> np.ndarray:
        """Bytes to remove, as a mask over the buffer. The arrays are runs of windows of snippets with an earlier document."""
        least = np.repeat(self.least[:, None], SPAN, axis=1)
        for s in range(SPAN):
            now = (start <= s) & (s < start + length)
            least[index[now], s] = np.minimum(least[index[now], s], doc[now])
        hit = (least[self.snippet] < self.doc[self.runs][:, None]) & (np.arange(SPAN)[None, :] < self.count[self.runs][:, None])
        run, offset = np.nonzero(hit)
        window = self.first[self.runs][run] + offset
        change = np.zeros(len(self.buffer) + 1, np.int64)
        np.add.at(change, window, 1)
        np.add.at(change, window + WINDOW, -1)
        return np.cumsum(change[:-1]) > 0


SIDE = "g long, kind int, p long, a binary, b binary"
_SIDE_TYPES = pa.schema([("g", pa.int64()), ("kind", pa.int32()), ("p", pa.int64()), ("a", pa.binary()), ("b", pa.binary())])


def _side(rows: list[tuple]) -> pa.Table:
    return pa.Table.from_pylist([dict(zip(_SIDE_TYPES.names, r, strict=True)) for r in rows], schema=_SIDE_TYPES)


def _known(group: Group, side: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """Flags of the group's codes from the buckets' answers: another group has it, very many have it."""
    flags, hot = np.zeros(len(group.codes), bool), np.zeros(len(group.codes), bool)
    for r in side.to_pylist():
        if r["kind"] == 0:
            a, b = np.searchsorted(group.codes, [r["p"] << 40, (r["p"] + 1) << 40])
            flags[a:b] = np.unpackbits(np.frombuffer(r["a"], np.uint8))[: b - a]
            if r["b"] is not None:
                hot[a:b] = np.unpackbits(np.frombuffer(r["b"], np.uint8))[: b - a]
    return flags, hot


def _pack(codes: np.ndarray) -> bytes:
    """Codes without their bucket, five bytes each."""
    return np.ascontiguousarray(codes.astype("<i8").view(np.uint8).reshape(-1, 8)[:, :5]).tobytes()


def _unpack(data: bytes) -> np.ndarray:
    own = np.frombuffer(data, np.uint8).reshape(-1, 5)
    full = np.zeros((len(own), 8), np.uint8)
    full[:, :5] = own
    return full.view("<i8")[:, 0]


def _send_codes(buckets: int):
    def run(table: pa.Table) -> pa.Table:
        group = Group(table, buckets)
        g, rows = table.column("g")[0].as_py(), []
        cut = np.searchsorted(group.codes, np.arange(buckets + 1) << 40)
        for p in np.flatnonzero(np.diff(cut)).tolist():
            rows.append((g, 0, p, _pack(group.codes[cut[p] : cut[p + 1]]), None))
        return _side(rows)

    return run


def _meet_codes(hot: int | None):
    """For each sender, a bit for each of its codes in this bucket: whether another one has it, and whether over ``hot`` have."""

    def run(table: pa.Table) -> pa.Table:
        parts = table.to_pylist()
        wide = [_unpack(r["a"]) for r in parts]
        values, counts = np.unique(np.concatenate(wide), return_counts=True)
        shared, many = values[counts > 1], values[counts > hot] if hot is not None else None
        bits = lambda w, v: np.packbits(np.isin(w, v, assume_unique=True)).tobytes()
        return _side([(r["g"], 0, r["p"], bits(w, shared), None if many is None else bits(w, many)) for r, w in zip(parts, wide, strict=True)])

    return run


def _merge_codes(cell: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
    """The distinct codes of a cell, as one sender."""
    return _side([(cell[1].as_py(), 0, cell[0].as_py(), _pack(np.unique(np.concatenate([_unpack(x) for x in table.column("a").to_pylist()]))), None)])


def _tell_cell(codes: pa.Table, told: pa.Table) -> pa.Table:
    """Answers for the groups of a cell: a code is shared inside the cell, or by another one."""
    if not codes.num_rows:
        return _side([])
    parts, (answer,) = codes.to_pylist(), told.to_pylist()
    wide = [_unpack(r["a"]) for r in parts]
    values, counts = np.unique(np.concatenate(wide), return_counts=True)
    flag = lambda name: np.unpackbits(np.frombuffer(answer[name], np.uint8))[: len(values)].astype(bool)
    shared, many = flag("a") | (counts > 1), flag("b")
    rows = []
    for r, w in zip(parts, wide, strict=True):
        at = np.searchsorted(values, w)
        rows.append((r["g"], 0, r["p"], np.packbits(shared[at]).tobytes(), np.packbits(many[at]).tobytes()))
    return _side(rows)


def _codec():
    return pa.Codec("zstd", compression_level=1)


def _send_snippets(buckets: int):
    """Snippets by bucket (kind 1); windows of those around hot anchors one by one (kind 2: ``p`` is the document, ``a`` the bytes)."""

    def run(text: pa.Table, side: pa.Table) -> pa.Table:
        if not text.num_rows:
            return _side([])
        group = Group(text, buckets)
        group.share(*_known(group, side))
        g, rows = text.column("g")[0].as_py(), []
        cold = np.flatnonzero(~group.hot)
        order = cold[np.argsort(group.snippet_bucket[cold], kind="stable")]
        cut = np.searchsorted(group.snippet_bucket[order], np.arange(buckets + 1))
        for p in np.flatnonzero(np.diff(cut)).tolist():
            own = order[cut[p] : cut[p + 1]]
            head = np.int64(len(own)).tobytes() + own.astype("<i4").tobytes() + group.least[own].astype("<i8").tobytes()
            rows.append((g, 1, p, _codec().compress(group.snippets[own].tobytes(), asbytes=True), head))
        for k in np.flatnonzero(group.hot).tolist():
            raw = group.snippets[k].tobytes()
            rows += [(g, 2, int(group.least[k]), raw[o : o + WINDOW], np.array([k, o], "<i4").tobytes()) for o in range(raw[SNIPPET])]
        return _side(rows)

    return run


def _sort_bucket(table: pa.Table) -> pa.Table:
    """For each group, the runs of windows of its snippets that occur in a document before the snippet's own first one."""
    parts = table.to_pylist()
    matrices, least, index, owner = [], [], [], []
    for k, r in enumerate(parts):
        n = int(np.frombuffer(r["b"], np.int64, 1)[0])
        index.append(np.frombuffer(r["b"], "<i4", n, 8))
        least.append(np.frombuffer(r["b"], "<i8", n, 8 + 4 * n))
        matrices.append(np.frombuffer(_codec().decompress(r["a"], n * (SNIPPET + 1)), np.uint8).reshape(n, SNIPPET + 1))
        owner.append(np.full(n, k))
    matrix, least, index, owner = (np.concatenate(x) for x in (matrices, least, index, owner))
    parts = [(r["g"], r["p"]) for r in parts]
    chosen, number = distinct_rows(matrix)
    matrix = matrix[chosen]
    low = np.full(len(chosen), _LAST)
    np.minimum.at(low, number, least)
    count = matrix[:, SNIPPET].astype(np.int64)
    row = np.repeat(np.arange(len(count)), count)
    offset = np.arange(len(row)) - np.repeat(np.cumsum(count) - count, count)
    order, new = sort_windows(matrix.ravel(), row * (SNIPPET + 1) + offset)
    heads = np.flatnonzero(new)
    lowest = np.minimum.reduceat(low[row[order]], heads)
    best = np.full((len(chosen), SPAN), _LAST)
    best[row[order], offset[order]] = np.repeat(lowest, np.diff(np.append(heads, len(row))))
    del matrix, matrices, table, order, new
    out: list[list[np.ndarray]] = [[] for _ in range(5)]
    for at in range(0, len(least), 50_000):
        own = best[number[at : at + 50_000]]
        earlier = own < least[at : at + 50_000, None]
        begin = earlier.copy()
        begin[:, 1:] &= ~(earlier[:, :-1] & (own[:, 1:] == own[:, :-1]))
        r, o = np.nonzero(begin)
        length = np.bincount(np.cumsum(begin.ravel())[earlier.ravel()] - 1, minlength=len(r))
        for x, y in zip(out, (r + at, o, length, own[r, o], owner[at + r]), strict=True):
            x.append(y)
    r, o, length, doc, by = (np.concatenate(x) for x in out)
    cut = np.searchsorted(by, np.arange(len(parts) + 1))
    rows = []
    for (g, p), a, b in zip(parts, cut.tolist(), cut[1:].tolist(), strict=False):
        if a < b:
            rows.append((g, 1, p, np.stack([index[r[a:b]], o[a:b], length[a:b]], axis=1).astype("<i4").tobytes(), doc[a:b].astype("<i8").tobytes()))
    return _side(rows)


RESULT = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"


def _finish(buckets: int, with_text: bool):
    def run(text: pa.Table, side: pa.Table) -> pa.Table:
        names = [x.split()[0] for x in RESULT.split(", ")] + ["kept"] * with_text
        types = [pa.int64()] * 4 + [pa.string()] + [pa.binary()] * with_text
        if not text.num_rows:
            return pa.Table.from_arrays([pa.array([], t) for t in types], names=names)
        group = Group(text, buckets)
        group.share(*_known(group, side))
        rows = side.to_pylist()
        runs = [(np.frombuffer(r["a"], "<i4").reshape(-1, 3), np.frombuffer(r["b"], "<i8")) for r in rows if r["kind"] == 1]
        if alone := [r for r in rows if r["kind"] == 3]:
            where = np.stack([np.frombuffer(r["b"], "<i4") for r in alone])
            runs.append((np.column_stack([where, np.ones(len(where), "<i4")]), np.array([r["p"] for r in alone])))
        where = np.concatenate([a for a, _ in runs]).astype(np.int64) if runs else np.zeros((0, 3), np.int64)
        docs = np.concatenate([b for _, b in runs]) if runs else np.zeros(0, np.int64)
        gone = group.covered(where[:, 0], where[:, 1], where[:, 2], docs)
        out = []
        for d, a, b in zip(group.docs.tolist(), group.starts[:-1].tolist(), group.starts[1:].tolist(), strict=True):
            own = gone[a:b]
            kept = group.buffer[a:b][~own].tobytes()
            spans = int(np.count_nonzero(own[1:] & ~own[:-1])) + int(b > a and own[0])
            out.append((None if d == _LAST else d, b - a, b - a - len(kept), spans, hashlib.sha256(kept).hexdigest(), kept)[: len(names)])
        return pa.Table.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), types, strict=True)], names=names)

    return run


def remove_repeats(documents: DataFrame, group_bytes: int = GROUP_BYTES, with_text: bool = False, cell: int = CELL, hot: int = HOT) -> DataFrame:
    """``doc_id, n_bytes, n_removed, n_spans, kept_sha256`` (and ``kept``, the bytes left) of every row of ``doc_id, text``.

    A byte goes if a window of 50 bytes over it also starts in a document with a smaller id, judged on the input.
    Null text is empty; rows with one id never remove from each other; null ids count as larger than any id. Texts
    shorter than a window lose nothing; an empty table gives an empty result.
    """
    rows = documents.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(_LAST)).alias("doc"), F.coalesce("text", F.lit("")).alias("text"))
    total = documents.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    groups = max(1, -(-total // group_bytes))
    texts = rows.select(F.pmod(F.xxhash64("doc", F.octet_length("text")), F.lit(groups)).alias("g"), "doc", "text")
    codes = texts.groupBy("g").applyInArrow(_send_codes(groups), SIDE)
    if groups <= cell:
        answers = codes.groupBy("p").applyInArrow(_meet_codes(None), SIDE)
    else:
        codes = codes.withColumn("cell", F.pmod("g", F.lit(-(-groups // cell))))
        merged = codes.groupBy("p", "cell").applyInArrow(_merge_codes, SIDE)
        told = merged.groupBy("p").applyInArrow(_meet_codes(hot), SIDE)
        answers = codes.groupBy("p", "cell").cogroup(told.groupBy("p", "g")).applyInArrow(_tell_cell, SIDE)
    snippets = texts.groupBy("g").cogroup(answers.groupBy("g")).applyInArrow(_send_snippets(groups), SIDE)
    if groups <= cell:
        found = snippets.groupBy("p").applyInArrow(_sort_bucket, SIDE)
    else:
        answers, snippets = materialize(answers, "repeat-answers"), materialize(snippets, "repeat-snippets")
        found = snippets.where("kind = 1").groupBy("p").applyInArrow(_sort_bucket, SIDE)
        alone = snippets.where("kind = 2")
        first = alone.groupBy("a").agg(F.min("p").alias("first"))
        alone = alone.join(first, "a").where("first < p").select("g", F.lit(3).alias("kind"), F.col("first").alias("p"), "a", "b")
        found = found.unionAll(alone)
    return texts.groupBy("g").cogroup(answers.unionAll(found).groupBy("g")).applyInArrow(_finish(groups, with_text), RESULT + ", kept binary" * with_text)


def query(spark, sf_dir):
    """op5: what every document loses to passages of earlier ones."""
    return remove_repeats(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
