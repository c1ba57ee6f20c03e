"""Annotators over detections, on top of the imaging surface."""
