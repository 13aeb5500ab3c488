"""Rule programs: language, analysis, compilation and evaluation."""
