"""Count-min sketches as column arithmetic, sizing rules, SQL functions."""
