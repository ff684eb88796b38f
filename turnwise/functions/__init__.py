"""Column functions: set algebra over commitments, chain verdicts, text edits, routing, scores."""
