"""Live narration and detections."""
