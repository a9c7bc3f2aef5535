"""The live side: slots, windows and the recorder grid over streams."""
