"""Running statistics and packages over streams of rows."""
