"""ripplegraph: clustering of weighted graphs by waves, as DataFrame plans."""
