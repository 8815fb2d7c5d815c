"""Schemas of the tables that pass between operators."""

STRINGS = "sid long, s string"
PATTERNS = "pid long, kind string, lit string"
CATALOG = "key string, len int, n long"
EDGES = "tier int, lo long, hi long, rep double"
WORDS = "tier int, layer int, word_idx int, word long"
PARAMETERS = "tier int, layer int, n_keys long, n_bits long, n_hashes int, fpr double"
RESIDUAL = "tier int, key string"
NODES = "node_id int, parent_id int, key string, ch string, tier int, first_child int, is_last boolean"
EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
