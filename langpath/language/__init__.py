"""Regular expressions, automata, grammars and recursive state machines; all small and on the driver."""
