"""Physical-plan helpers: staging, batching, overlap and the outer loop."""
