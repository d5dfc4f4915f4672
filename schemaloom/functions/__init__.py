"""Column functions of the engine under one roof, for use in any plan."""

from schemaloom.operators.affinity import jaccard
from schemaloom.operators.asks import render_prompt
from schemaloom.operators.attributes import extract_paths, parse_mapping
from schemaloom.operators.hierarchy import align_name, extract_path, malformed
from schemaloom.operators.sampling import digest, kind, rule_cardinality

__all__ = ["align_name", "digest", "extract_path", "extract_paths", "jaccard", "kind", "malformed", "parse_mapping", "render_prompt", "rule_cardinality"]
