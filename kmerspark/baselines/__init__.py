"""The counters and trimmers that the sketch is compared with, behind one interface."""
