"""SQL that gives the same rows as the engine, over the whole graph at once: what one device would compute."""
