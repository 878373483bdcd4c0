"""The method's operators: entities, strength and expansion, walks, supervision, baselines, erasure."""
