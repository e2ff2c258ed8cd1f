"""Methods and operators: lineage, provenance, leakage, attribution, scores, curation, relational."""
