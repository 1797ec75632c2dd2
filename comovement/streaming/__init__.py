"""The join over streams of points (an extension: event time, watermarks, bounded state)."""
