"""Counting, sketching, recovery, baselines and measures as DataFrame operators."""
