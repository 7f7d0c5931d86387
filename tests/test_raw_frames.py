"""Binary frames: round trip through files, and what breaks them."""

from __future__ import annotations

import numpy as np
import pytest
from tissuemap.sources import raw_frames


def test_files_round_trip(spark, tmp_path):
    rng = np.random.default_rng(1)
    want = []
    for s in range(3):
        content = b""
        for t in range(4):
            n = int(rng.integers(0, 6))
            ku, kv, re, im = rng.integers(-300, 300, n), rng.integers(-300, 300, n), rng.normal(size=n).astype(np.float32), rng.normal(size=n).astype(np.float32)
            content += raw_frames.frame(s, 1, t, ku, kv, re, im)
            want += [(s, 1, t, int(a), int(b), float(c), float(d)) for a, b, c, d in zip(ku, kv, re, im, strict=True)]
        (tmp_path / f"{s}.raw").write_bytes(content)
    (tmp_path / "empty.raw").write_bytes(b"")
    (tmp_path / "other.txt").write_bytes(b"not a frame")
    got = raw_frames.read(spark, str(tmp_path))
    assert sorted(tuple(r) for r in got.collect()) == sorted(want)
    again = raw_frames.parse(raw_frames.pack(got))
    assert sorted(tuple(r) for r in again.collect()) == sorted(want)


def test_broken_frames_name_their_file():
    good = raw_frames.frame(1, 0, 2, [1], [2], [0.5], [0.25])
    for content in (good[:-1], good[:7], b"xxxx" + good[4:], good + b"\0"):
        with pytest.raises(ValueError, match="at byte .* of name"):
            list(raw_frames.frames(content, "name"))
