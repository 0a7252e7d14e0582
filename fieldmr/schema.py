"""Fixed row types; shape metadata is data, nothing is inferred."""

CELL = "snapshot string, field string, level int, x int, y int, z int, v double"
BLOCK = "level int, key long, vals array<double>"
CHUNK = "level int, chunk long, keys array<long>, vals array<double>"
PACKET = "level int, chunk long, codec string, keys array<long>, body binary, raw_bytes long, packed_bytes long, vmin double, vmax double, settings string, intensity array<double>"
PAIR = "level int, x int, y int, z int, orig double, deco double"
ERRMODEL = "iso double, n long, mu double, sigma double, tau double"
ISOCELL = "x int, y int, z int, crossed boolean, p double"
RDPOINT = "variant string, level int, eb double, n long, packed_bytes long, sse double, vmin double, vmax double, max_err double"
EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
