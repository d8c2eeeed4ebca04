"""Methods: truth, rendering, colour algebra, segmentation, text, learned parts, baselines, measures."""
