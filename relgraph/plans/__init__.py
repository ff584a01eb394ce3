"""How queries run: fixpoints over written states, query sets, deterministic reach, experiments."""
