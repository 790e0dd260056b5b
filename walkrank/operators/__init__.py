"""Methods, variants, baselines and measures as DataFrame operators."""
