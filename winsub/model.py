"""Schemas of the tables that operators take and give."""

SYMBOLS = "stream_id string, seq bigint, ts timestamp, sym string"
CHUNKS = "stream_id string, chunk_no bigint, base_off bigint, text string"
WINDOWS = "stream_id string, n_seen bigint, win_start bigint, win_text string"
QUERIES = "query_id string, stream_id string, pattern string, at_seq bigint"
MATCHES = "stream_id string, query_id string, n_seen bigint, off bigint"
TAILS = "stream_id string, n_seen bigint, tail_start bigint, tail_len bigint, kind string, twin bigint, period bigint"
SEGMENTS = "stream_id string, seg_no bigint, base_off bigint, text string, overlap string, sig binary, sa binary"


def names(schema: str) -> list[str]:
    return [x.strip().split(" ")[0] for x in schema.split(",")]
