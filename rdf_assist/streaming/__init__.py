"""The methods over streams of keystrokes and events."""
