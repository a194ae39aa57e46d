"""Physical operators: graph fixpoints, unification, grounding, coordination."""
