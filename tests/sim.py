"""The indexing loop, document by document, with real buffers: what the batch form must equal. Test use only."""

from __future__ import annotations

import re

from postpool.functions.codec import pfor_encode


def words(text):
    return [w for w in re.split(r"[\W_]+", (text or "").lower()) if w]


def blocks_of(postings, block, positional=True):
    docs = [d for d, _ in postings]
    gaps = [b - a for a, b in zip([0, *docs], docs)]
    flat = []
    for _, pos in postings:
        flat += [b - a for a, b in zip([0, *pos], pos)]
    p = [pfor_encode(flat[i : i + block]) for i in range(0, len(flat), block)] if positional else []
    return pfor_encode(gaps), pfor_encode([len(pos) for _, pos in postings]), p


def simulate(docs, block, cap, threshold):
    """(dictionary, segments): segments as dicts in pool order, with addresses and next pointers."""
    order, buffers, level, df, pool, end, last = [], {}, {}, {}, [], 0, {}

    def flush(term):
        nonlocal end
        postings = buffers[term]
        for i in range(0, len(postings), block):
            d, f, p = blocks_of(postings[i : i + block], block)
            n = 8 + 4 + len(d) + 4 + len(f) + sum(4 + len(x) for x in p)
            seg = {"term": term, "seg_no": 0 if term not in last else last[term]["seg_no"] + 1, "group_no": level[term], "addr": end, "next_addr": None, "n_bytes": n, "blocks": (d, f, p)}
            if term in last:
                last[term]["next_addr"] = end
            last[term] = seg
            pool.append(seg)
            end += n
        buffers[term] = []
        level[term] += 1

    for doc, text in docs:
        places = {}
        for i, w in enumerate(words(text), 1):
            places.setdefault(w, []).append(i)
        for term, pos in places.items():
            if term not in buffers:
                buffers[term], level[term], df[term] = [], 0, 0
                order.append(term)
            df[term] += 1
            buffers[term].append((doc, pos))
            if len(buffers[term]) == block << min(level[term], cap):
                flush(term)
    kept = [t for t in order if df[t] >= threshold]
    for term in kept:
        if buffers[term]:
            flush(term)
    return {t: (i, df[t]) for i, t in enumerate(kept)}, pool
