"""The pipeline's stages against plain Python, each on its own input."""

import collections
import hashlib
import math
import re

import numpy as np
import sentencepiece

from rankpress.llm import mixing, pieces, quality, toxicity

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def grams(text):
    w = WORD.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
    return {" ".join(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def one_of_each_group(rows):
    sets = [grams(r.text) for r in rows]
    group = {r.doc_id: r.doc_id for r in rows}
    for i, a in enumerate(rows):
        for j in range(i):
            b, same = rows[j], len(sets[i] & sets[j])
            if (not sets[i] and not sets[j]) or (same and same >= 0.8 * (len(sets[i]) + len(sets[j]) - same)):
                x, y = group[a.doc_id], group[b.doc_id]
                group = {k: min(x, y) if v in (x, y) else v for k, v in group.items()}
    return {r.doc_id for r in rows if group[r.doc_id] == r.doc_id}


def mixed_by_hand(rows, slots=1 << 18):
    """How often each document stays: targets by filling up, blocks end to end, points of the van der Corput sequence one by one."""
    size = {r.doc_id: len(WORD.findall(r.text or "")) for r in rows}
    names = sorted({r.source for r in rows}, key=lambda n: (n is None, n))
    total = {n: sum(size[r.doc_id] for r in rows if r.source == n) for n in names}
    weight, capped, every = {n: (3, 1, 2)[k % 3] for k, n in enumerate(names)}, {}, 1.5 * sum(total.values())
    while True:
        free = [n for n in names if n not in capped]
        unit = (every - sum(capped.values())) / sum(weight[n] for n in free) if free else 0
        over = {n: 2.0 * total[n] for n in free if unit * weight[n] > 2 * total[n]}
        if not over:
            break
        capped |= over
    words = {n: math.floor(capped.get(n, unit * weight[n]) + 1e-6) for n in names}
    block = max(1, math.ceil(sum(words.values()) / slots))
    blocks = {n: math.ceil(total[n] / block) for n in names}
    need = {n: math.ceil(words[n] / block) if words[n] <= total[n] else blocks[n] + math.ceil((words[n] - total[n]) / block) for n in names}
    first, at = {}, 0
    for n in names:
        first[n], at = at, at + need[n]
    bits = math.ceil(math.log2(max(2, at)))
    took = {n: collections.Counter() for n in names}
    given = dict.fromkeys(names, 0)
    for slot in range(1 << bits):
        point = int(f"{slot:0{bits}b}"[::-1], 2)
        for n in names:
            if first[n] <= point < first[n] + need[n]:
                r = given[n]
                given[n] += 1
                turn, k = divmod(r, blocks[n])
                left = (min(words[n], total[n]) if not turn else words[n] - total[n]) - k * block
                for w in range(k * block, k * block + min(block, left)):
                    took[n][w] += 1
    times = {}
    for n in names:
        pos = 0
        for r in sorted((r for r in rows if r.source == n), key=lambda r: (hashlib.md5(str(r.doc_id).encode()).hexdigest(), r.doc_id)):
            if size[r.doc_id]:
                got = sum(took[n][w] for w in range(pos, pos + size[r.doc_id]))
                times[r.doc_id] = math.floor(got / size[r.doc_id] + 0.5)
            pos += size[r.doc_id]
    return {d: t for d, t in times.items() if t}


def test_stages_against_plain_python(spark, sf):
    import corpus_pipeline as c

    docs, labels = spark.read.parquet(f"{sf}/documents.parquet").where("doc_id < 120"), spark.read.parquet(f"{sf}/labels.parquet")
    stage = dict(c.STAGES)
    rows = docs.collect()
    m = toxicity.learn(docs, labels)
    kept = stage["toxicity"](spark, docs, sf)
    assert {r.doc_id for r in kept.collect()} == {r.doc_id for r in rows if m.scores([r.text])[0] < 0.5}
    m = quality.learn(docs, labels)
    kept = stage["quality"](spark, docs, sf)
    assert {r.doc_id for r in kept.collect()} == {r.doc_id for r in rows if m.scores(np.array([quality.statistics(r.text)]))[0] >= 0.3}
    kept = stage["near_copies"](spark, docs, sf)
    assert {r.doc_id for r in kept.collect()} == one_of_each_group(rows) != {r.doc_id for r in rows}
    out = stage["mixing"](spark, docs, sf).collect()
    assert collections.Counter(r.doc_id for r in out) == collections.Counter(mixed_by_hand(rows))
    for slots in (64, 1024):
        assert collections.Counter(r.doc_id for r in mixing.mixed(docs, slots).collect()) == collections.Counter(mixed_by_hand(rows, slots))
    lib = sentencepiece.SentencePieceProcessor(model_file=pieces.MODEL_PATH)
    text = {r.doc_id: r.text for r in rows}
    for r in stage["sentencepiece"](spark, docs, sf).collect():
        assert r.ids == lib.encode(text[r.doc_id])
