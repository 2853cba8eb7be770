"""Schemas of the derived tables. Positions are 1-based; every text is closed by a virtual sentinel at position n + 1."""

ARRAYS = "text_id {id}, pos long, isa long, phi long, plcp long, bwt string"
REACH_STEPS = "text_id {id}, pos long, reach long"
LPF = "text_id {id}, pos long, lpf long, prev_src long"
PEAKS = "text_id {id}, pos long, plcp long, is_interesting boolean, is_maximal boolean"
FACTORS = "text_id {id}, factor_no long, dst long, len long, src long, literal string"
REFERENCES = "text_id {id}, dst long, len long, src long"
TILES = "text_id {id}, dst long, src long, len long, final boolean"
TEXTS = "text_id {id}, text string"
