"""Column lists of every stage, as DDL."""

READINGS = "stream_id bigint, pos int, sym bigint"
BLOCKS = "stream_id bigint, block_no int, n_readings int, readings array<bigint>"
STREAMS = "stream_id bigint, block_no int, coder string, n_readings int, n_bits bigint, mu int, sigma int, first bigint, words array<int>"
VECTORS = "batch_id bigint, stream_id bigint, vec array<double>"
ASSIGNED = "batch_id bigint, stream_id bigint, cluster_id int, dist2 double"
PACKED = (
    "batch_id bigint, window_no int, k int, cluster_id int, part int, grouping string, config string, stream_ids array<bigint>, stream_lengths array<int>, "
    "n_symbols bigint, rle_applied boolean, rle_threshold int, streams_meta binary, alphabet binary, model binary, payload binary, "
    "payload_bits bigint, side_bits bigint, orig_bits bigint, raw_bits bigint, crc bigint"
)
