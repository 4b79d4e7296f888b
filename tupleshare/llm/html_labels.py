"""Pages of common layouts, labelled by hand: what stands before the main content, the content, what stands after it."""

LABELLED = [
    (
        '<html><head><title>Rivers in spring</title><style>p{margin:0}</style><script>init(1)</script></head><body><nav><ul><li><a href="/a">Home</a></li><li><a href="/b">News</a></li><li><a href="/c">About us</a></li></ul></nav><div class="ad">Buy our excellent boots now and save</div><article>',
        "<h1>Rivers in spring</h1><p>When the snow melts the rivers rise fast, and people who live along the banks watch the gauges day and night.</p><p>The water carries wood, stones and <b>sand</b> to the plain.<br>Older maps show where it went before.</p><p>A good year leaves rich soil behind.</p>",
        "</article><footer>&copy; example.org &middot; all texts are free</footer></body></html>",
    ),
    (
        '<html><body><header><div class="logo"><a href="/">The Daily</a></div><ul class="menu"><li><a href="/w">World</a></li><li><a href="/s">Sport</a></li></ul></header><div id="cookie-notice"><p>We use cookies to make this site work.</p><button>OK</button></div><main>',
        '<h1>A bridge opens</h1><div class="lead"><p>The new bridge took six years to build and opened on Monday with a short walk of the two mayors.</p></div><h2>Cost</h2><p>It cost less than planned, the council said, because steel had become cheaper.</p><ul><li>Length: 420 metres</li><li>Height: 31 metres</li></ul><blockquote>We waited long for this day.</blockquote>',
        '</main><aside class="sidebar"><h3>Most read</h3><ul><li><a href="/1">Rain is coming</a></li><li><a href="/2">Market closes</a></li></ul></aside><section class="comments"><h3>Comments</h3><div class="comment"><p>I like the bridge very much.</p></div><div class="comment"><p>Too late, and too far from the town.</p></div></section><footer><p>Contact, terms and privacy</p></footer></body></html>',
    ),
    (
        '<html><body><div class="navbar"><a href="/">Start</a> <a href="/faq">Questions</a> <a href="/in">Log in</a></div><form action="/find"><label>Search</label><input name="q"><button>Go</button></form><table><tr><td>',
        "<h2>How to plant beans</h2><p>Soak the beans in water for a night before you put them into the ground.</p><p>Dig a hole as deep as your thumb.<p>Put three beans in each, and water them every second day until they show.<p>Poles help them to climb.",
        '</td><td class="sidebar"><div class="advert">Seeds at half the price</div><div class="newsletter">Subscribe to our letter<form><input><button>Send</button></form></div></td></tr></table><div class="footer"><a href="/t">Terms</a> | <a href="/p">Privacy</a></div></body></html>',
    ),
    (
        '<body><ul><li><a href="/1">One</a></li><li><a href="/2">Two</a></li><li><a href="/3">Three</a></li><li><a href="/4">Four</a></li></ul><div><a href="/x">Sign up</a><a href="/y">Help</a></div><div>',
        "<p>The library keeps its old catalogue on cards, and a clerk still adds a card for each book that comes in.</p><p>Readers may look at the cards, but must not take them out of the drawers, since a lost card is a lost book.</p><p>In the cellar there are two more rooms with maps and papers of the town.</p>",
        '</div><div><a href="/m">More</a><a href="/n">Next page</a></div><ul><li><a href="/5">Five</a></li><li><a href="/6">Six</a></li></ul><div class="social">Share this</div></body>',
    ),
    (
        '<html><body><div id="top"><a href="/">Forum</a> &gt; <a href="/g">Garden</a></div><div><a href="/r">Register</a> <a href="/i">Sign in</a> <a href="/q">Help</a></div><div>',
        "<h2>My apple tree drops its leaves</h2><p>It stands in the sun and gets water twice a week, yet since July it loses leaves, and those that stay have brown edges.</p><p>A neighbour says the <a href=\"/soil\">soil</a> is too wet. Should I dig a trench, or wait until autumn?</p>",
        '</div><div><a href="/p1">1</a> <a href="/p2">2</a> <a href="/p3">3</a> <a href="/p4">Next</a></div><div class="replies"><p>Wait until autumn, and water less.</p></div><p><a href="/imprint">Imprint</a> <a href="/rules">Rules</a></p></body></html>',
    ),
    (
        '<html><body><table width="100%"><tr><td colspan="2"><img src="/l.gif"></td></tr><tr><td><a href="/1">Tides</a><br><a href="/2">Winds</a><br><a href="/3">Charts</a><br><a href="/4">Links</a></td><td>',
        "<h1>Sailing round the cape</h1><p>The current runs north for six hours and south for six, and only near the turn can a small boat pass.<br>Leave the harbour two hours before.<table><tr><th>Wind</th><th>Wait</th></tr><tr><td>west</td><td>one day</td></tr><tr><td>east</td><td>none</td></tr></table><p>Keep the light to your left until the second buoy, then turn and follow the coast.",
        '</td></tr><tr><td colspan="2"><a href="/5">Guest book</a> | <a href="/6">Mail</a> | <a href="/7">Map</a></td></tr></table></body></html>',
    ),
    (
        '<html><body><div class="layout"><ul><li><a href="#a">Install</a></li><li><a href="#b">First steps</a></li><li><a href="#c">Options</a></li><li><a href="#d">Errors</a></li><li><a href="#e">Index</a></li></ul><section>',
        '<h1>Options</h1><p>Every option may stand in the file or on the command line, and the command line wins.</p><dl><dt>depth</dt><dd>How many levels of folders are read.</dd><dt>quiet</dt><dd>Nothing is written but errors.</dd></dl><pre>scan --depth 3 notes</pre><p>Options that are not known end the program with an error.</p>',
        '</section><div><a href="/prev">Previous</a> <a href="/next">Next</a></div><ul><li><a href="/x1">Version 1</a></li><li><a href="/x2">Version 2</a></li></ul></div></body></html>',
    ),
    (
        '<html><body><div><a href="/"><img src="/logo.png"></a> <a href="/soups">Soups</a> <a href="/cakes">Cakes</a></div><main>',
        "<h1>Plum cake</h1><p>This cake keeps for a week and is best on the second day.</p><h2>You need</h2><ul><li>1 kg of plums</li><li>300 g of flour</li><li>150 g of butter</li><li>2 eggs</li></ul><h2>Steps</h2><ol><li>Rub the butter into the flour and add the eggs.</li><li>Lay the plums on the dough, close to each other.</li><li>Bake for fifty minutes.</li></ol>",
        '</main><div><h4>More cakes</h4><a href="/c1"><img src="/1.jpg">Apple cake</a><a href="/c2"><img src="/2.jpg">Pear cake</a><a href="/c3"><img src="/3.jpg">Nut cake</a></div><div><a href="/about">About</a><a href="/contact">Contact</a></div></body></html>',
    ),
]
