"""Column functions: tokens, scores, codes. They stay inside generated code."""
