import hashlib
import random
import zlib

import numpy as np
from chronolode.llm import media as m
from fixtures import documents, empty, rows_of


def test_round_trip_and_index():
    r = random.Random(1)
    for n in (0, 1, 63, 64, 65, 4096, 4097, 70_000):
        payload = m.padded(r.randbytes(n))
        file = m.write_avi(payload)
        assert len(payload) % 64 == 0 and b"".join(f.tobytes() for f in m.decode(file)) == payload
        cut = file[: file.index(b"idx1")]
        assert m.frame_bytes(cut) == m.frame_bytes(file)  # without an index the list is walked


def test_general_huffman_and_baseline_frames():
    frame = m.frame_bytes(m.write_avi(m.padded(b"hello world" * 9)))[0]
    fast = m.decode_frame(frame)
    keep, m.TABLE = m.TABLE, b"\0" * 30
    try:
        assert (m.decode_frame(frame) == fast).all()
    finally:
        m.TABLE = keep
    # A baseline frame of one flat block: difference of category 7 (code 0), value 100, then end of block (code 0).
    dht = lambda c, s: b"\xff\xc4" + (19 + 1).to_bytes(2, "big") + bytes([c]) + bytes([1] + [0] * 15) + bytes([s])
    head = b"\xff\xd8\xff\xdb\x00\x43\x00" + bytes([8] * 64) + dht(0x00, 7) + dht(0x10, 0) + b"\xff\xc0\x00\x0b\x08\x00\x08\x00\x08\x01\x01\x11\x00\xff\xda\x00\x08\x01\x01\x00\x00\x3f\x00"
    got = m.decode_frame(head + bytes([0b01100100, 0b01111111]) + b"\xff\xd9")
    assert got.shape == (8, 8) and (got == 128 + 100).all()


def test_shots_are_cut_where_histograms_change():
    dark, light = np.full((64, 64), 10, np.uint8), np.full((64, 64), 200, np.uint8)
    assert m.clips([dark] * 5 + [light] * 4 + [dark] * 3) == [(0, 4), (5, 8), (9, 11)]
    assert m.clips([]) == [] and m.clips([dark]) == [(0, 0)]


def test_rows(spark):
    docs = documents(spark)
    got = sorted((r.doc_id or -1, r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) for r in m.read_back(m.media_column(docs)).collect())
    want = sorted((d or -1, len(t.encode()), len(p := m.padded(t.encode())), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:])) for d, t, _ in rows_of(docs))
    assert got == want
    assert m.clip_rows(m.media_column(docs)).filter("last_frame >= first_frame AND end_s > start_s").count() >= docs.count()
    assert m.read_back(m.media_column(empty(spark))).count() == 0
    broken = spark.createDataFrame([(1, 3, b"RIFF"), (2, 0, None)], "doc_id long, n_bytes long, media binary")
    assert [r.payload_bytes for r in m.read_back(broken).collect()] == [None, None] and m.clip_rows(broken).count() == 0


def slow_clips(frames):
    """Cuts by plain loops: a histogram of 16 bins a frame, differences measured against those of the same shot, as far back as the window."""
    hists = []
    for f in frames:
        h = [0] * m.BINS
        for x in f.ravel().tolist():
            h[x * m.BINS // 256] += 1
        hists.append([x / f.size for x in h])
    diffs, starts = [sum(abs(a - b) for a, b in zip(x, y, strict=True)) for x, y in zip(hists, hists[1:], strict=False)], [0]
    for i, d in enumerate(diffs):
        past = diffs[max(starts[-1], i - m.WINDOW) : i]
        mean = sum(past) / len(past) if past else 0
        if d > m.LEAST and (not past or d > mean + m.DEVIATIONS * (sum((x - mean) ** 2 for x in past) / len(past)) ** 0.5):
            starts.append(i + 1)
    return list(zip(starts, [x - 1 for x in starts[1:]] + [len(frames) - 1], strict=True)), [sum(x.ravel().tolist().count(v) for x in frames for v in range(b * 16, b * 16 + 16)) for b in range(m.BINS)]


def test_clips_and_features_match_plain_loops(spark):
    r = random.Random(7)
    texts = ["".join(r.choice(a) * 37 for a in (r.choice(["ab", "XYZ", "0189", "éß"]) for _ in range(r.randrange(1, 40)))) * 9 for _ in range(8)] + ["", None, "z" * 40_000 + "A" * 40_000]
    docs = documents(spark, texts)
    by = {d: t for d, t, _ in rows_of(docs) if d is not None}
    clips = {}
    for x in m.clip_rows(m.media_column(docs.dropDuplicates(["doc_id"]))).collect():
        clips.setdefault(x.doc_id, []).append((x.clip, x.first_frame, x.last_frame, x.start_s, x.end_s))
    feature = {x.doc_id: x.feature for x in m.read_back(m.media_column(docs)).collect()}
    cuts = 0
    for d, t in by.items():
        frames = m.decode(m.write_avi(m.padded(t.encode())))
        want, hist = slow_clips(frames)
        cuts += len(want) - 1
        assert sorted(clips[d]) == [(i, a, b, a / m.FPS, (b + 1) / m.FPS) for i, (a, b) in enumerate(want)]
        assert feature[d].endswith("hist=" + ",".join(map(str, hist))) and f"frames={len(frames)};" in feature[d]
    assert cuts


def test_very_long_text(spark):
    text = "long text. " * 200_000
    (row,) = m.read_back(m.media_column(documents(spark, [text]).filter("doc_id = 0").dropDuplicates())).collect()
    assert row.payload_sha256 == hashlib.sha256(m.padded(text.encode())).hexdigest()
