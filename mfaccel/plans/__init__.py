"""Physical layout: blocks, routing, and what a plan exchanges."""
