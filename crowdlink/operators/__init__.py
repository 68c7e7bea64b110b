"""Methods, baselines and measures as DataFrame operators."""
