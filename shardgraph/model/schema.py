"""Schemas of the engine's tables, as DDL."""

EDGES = "src long, dst long, weight long"
INTERVALS = "shard_id int, lo long, hi long, edges long"
CSR = "shard_id int, lo long, hi long, row array<long>, col array<long>, val array<long>"
PAYLOAD = "shard_id int, codec string, raw_bytes long, payload binary"
LEDGER = "run string, model string, app string, iter int, phase string, active long, shards_total int, shards_read int, cache_hits int, read_rows long, read_bytes long, write_rows long, write_bytes long, seconds double"
#: Bytes of a vertex record (a double or long) and of an edge record (a 64-bit source), as the ledgers count them.
VERTEX_BYTES, EDGE_BYTES = 8, 8
